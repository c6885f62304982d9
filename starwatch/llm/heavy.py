"""Joining statistics back to rows when a few keys may hold most rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SALTS = 64


def join_back(rows: DataFrame, table: DataFrame, key: str, weight: str, dice: Column) -> DataFrame:
    """``rows`` left joined with ``table`` (a written table; one row per ``key``, with the rows it stands for as ``weight``).

    Only keys with more than 1 / SALTS of all rows, so fewer than SALTS of them, are salted:
    their rows of ``table`` stand once per salt, and ``dice`` (a whole number) deals out the other side.
    """
    total = table.agg(F.sum(weight)).first()[0] or 0
    heavy = [r[0] for r in table.filter(F.col(weight) * SALTS > total).select(key).collect()]
    is_heavy = F.col(key).isin(heavy) if heavy else F.lit(False)
    salted = rows.withColumn("_salt", F.when(is_heavy, F.pmod(dice, F.lit(SALTS))).otherwise(0).cast("int"))
    salts = F.when(is_heavy, F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))
    other = table.drop(weight).withColumn("_key_salt", F.explode(salts)).withColumnRenamed(key, "_key")
    return salted.join(other, (salted[key] == other._key) & (salted._salt == other._key_salt), "left").drop("_key", "_salt", "_key_salt")
