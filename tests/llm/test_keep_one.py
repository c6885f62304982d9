"""One row of each component where ids are null or shared."""

from starwatch.llm import paritysketch


def test_unrelated_texts_with_null_or_shared_ids_stay(spark):
    text = [" ".join(f"{c}{i}" for i in range(40)) for c in "abcdefg"]
    near = text[5] + " more"
    rows = [(None, text[0]), (None, text[1]), (None, text[2]), (5, text[3]), (5, text[4]), (9, text[5]), (3, near), (None, near), (None, text[6]), (None, text[6]), (8, None), (None, ""), (None, " ")]
    got = [tuple(r) for r in paritysketch.keep_one(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()]
    want = {(None, text[0]), (None, text[1]), (None, text[2]), (5, text[3]), (5, text[4]), (3, near), (None, text[6]), (8, None), (None, ""), (None, " ")}
    assert set(got) == want and len(got) == len(want)
