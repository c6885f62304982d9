"""The band synopsis: a grid over upper corners per degree band, stored by band, label and cell key."""

from __future__ import annotations

from copy import copy
from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import embedding_columns, label_dict
from ..model import BuildParams, Graph
from ..storage import materialise, side_by_side
from .bands import corners_and_boxes, degree_bands
from .stars import add_counts, neighbour_histogram, neighbour_sums, signed_counts, stars

SENTINEL = (1 << 63) - 1


def grid_of(corners: DataFrame, p: BuildParams) -> DataFrame:
    """band, g_lo*, g_w*: the origin and cell width of each dimension, a row per band."""
    mins = [F.min(f"ub{k}").alias(f"g_lo{k}") for k in p.dims]
    widths = [(F.expr(f"(max(ub{k}) - min(ub{k})) div {p.k}") + 1).alias(f"g_w{k}") for k in p.dims]
    return corners.groupBy("band").agg(*mins, *widths)


def place_in_grid(corners: DataFrame, grid: DataFrame, p: BuildParams) -> DataFrame:
    """Adds cell (its indexes), cu* (the cell's upper corner) and cell_key (sum of the corner's squares).

    The last cell of a dimension has no upper end, so vectors may grow past the first
    graph's; its corner is a sentinel and its key infinite.
    """
    rows = corners.join(F.broadcast(grid), "band")
    index = [F.expr(f"least({p.k - 1}L, greatest(0L, (ub{k} - g_lo{k}) div g_w{k}))") for k in p.dims]
    rows = rows.withColumns({f"_c{k}": x for k, x in enumerate(index)})
    rows = rows.withColumns({f"cu{k}": F.when(F.col(f"_c{k}") == p.k - 1, F.lit(SENTINEL)).otherwise(F.col(f"g_lo{k}") + (F.col(f"_c{k}") + 1) * F.col(f"g_w{k}") - 1) for k in p.dims})
    open_cell = " OR ".join(f"_c{k} = {p.k - 1}" for k in p.dims)
    squares = " + ".join(f"CAST(cu{k} AS DOUBLE) * CAST(cu{k} AS DOUBLE)" for k in p.dims)
    key = F.expr(f"CASE WHEN {open_cell} THEN CAST('Infinity' AS DOUBLE) ELSE {squares} END")
    rows = rows.withColumn("cell_key", key).withColumn("cell", F.concat_ws("-", *[F.col(f"_c{k}") for k in p.dims]))
    return rows.select("band", "cell", "cell_key", *[f"cu{k}" for k in p.dims], "v", "label", "deg", *[f"ub{k}" for k in p.dims])


#: Epochs whose rows stand beside an index's written tables before the tables are written anew.
PIECES = 4


class Index:
    """Everything query answering reads: stars, bands, synopsis and boxes of one snapshot. A table is made, and
    written, when it is first asked for."""

    depth = 0

    def __init__(self, g: Graph, p: BuildParams, deltas: DataFrame, t: int | None = None, bands: DataFrame | None = None, grid: DataFrame | None = None):
        self.graph, self.params, self.t, self.deltas = g, p, t, deltas
        for name, table in (("bands", bands), ("grid", grid)):
            if table is not None:
                setattr(self, name, table)

    @cached_property
    def dictionary(self) -> DataFrame:
        return label_dict(self.graph.vertices if self.graph.vertex_life is None else self.graph.vertex_life, self.params)

    @cached_property
    def hist(self) -> DataFrame:
        return materialise(neighbour_histogram(self.graph, self.t, self.params.elabel_weight), "hist")

    @cached_property
    def star(self) -> DataFrame:
        return materialise(stars(self.graph, self.params, self.t, self.hist), "star")

    @cached_property
    def bands(self) -> DataFrame:
        return materialise(degree_bands(self.star, self.params.m), "bands")

    @cached_property
    def grid(self) -> DataFrame:
        return materialise(grid_of(self.corners, self.params), "grid")

    @cached_property
    def _corners_and_boxes(self) -> tuple[DataFrame, DataFrame]:
        runs = self.hist if not self.params.elabel_weight else self.hist.groupBy("v", "nlabel").agg(F.sum("cnt").cast("int").alias("cnt"))
        return corners_and_boxes(runs, self.star, self.bands, self.deltas, self.params, self.dictionary)

    @cached_property
    def corners(self) -> DataFrame:
        return self._corners_and_boxes[0]

    @cached_property
    def boxes(self) -> DataFrame:
        return self._corners_and_boxes[1]

    @cached_property
    def synopsis(self) -> DataFrame:
        return materialise(place_in_grid(self.corners, self.grid, self.params), "synopsis")

    def prepare(self) -> None:
        """What every epoch reads is written: the counters, the bands and the grid."""
        side_by_side(lambda: self.hist, lambda: self.dictionary)
        assert self.hist is not None and self.bands is not None and self.grid is not None

    def changed(self, ops: DataFrame, vertices: DataFrame | None = None, moved: DataFrame | None = None, relabelled: DataFrame | None = None) -> Index:
        """The index's rows of the ends of updated edges only, after normalised updates (op, u, v), with the bands and
        the grid as they are: their counters are changed, and their stars, corners, cells and boxes made anew from the counters.

        ``vertices`` adds new ones and holds new labels. ``moved`` (u, v): all edges, of before the updates, at the vertices
        ``relabelled`` (v) whose label changed; they leave under the old labels and come back under the new ones.
        """
        if self.params.elabel_weight:
            raise NotImplementedError("counters by edge label are not kept up")
        vertices = self.graph.vertices if vertices is None else vertices
        signed, t = signed_counts(ops, vertices), touched(ops)
        if moved is not None:
            out, in_ = (moved.select(F.lit(op).alias("op"), "u", "v") for op in "-+")
            signed = signed.unionByName(signed_counts(out, self.graph.vertices)).unionByName(signed_counts(in_, vertices))
            t = t.unionByName(touched(moved)).unionByName(relabelled.select("v")).distinct()
        return Part(self, vertices, signed, materialise(t, "touched"))

    def merged(self, part: Part) -> Index:
        """The whole index with the rows of ``part`` (see ``changed``); all others are carried over."""
        return Merged(self, part)

    def advance(self, ops: DataFrame, vertices: DataFrame | None = None) -> Index:
        """The index after normalised updates (op, u, v); only the ends of updated edges are worked on."""
        return self.merged(self.changed(ops, vertices))

    @property
    def n_touched(self) -> int:
        """Vertices that the last updates were at."""
        return self.touched.count()

    def of_vertices(self, t: DataFrame) -> Index:
        """The index's rows of some vertices (v)."""
        out = copy(self)
        out.bands, out.grid = self.bands, self.grid
        for name in ("hist", "star", "corners", "synopsis", "boxes"):
            setattr(out, name, getattr(self, name).join(t, "v", "left_semi"))
        return out

    def cells(self) -> DataFrame:
        """One row per occupied cell, by band and falling key."""
        p = self.params
        return self.synopsis.groupBy("band", "cell", "cell_key", *[f"cu{k}" for k in p.dims]).agg(F.count(F.lit(1)).alias("n_vertices"))

    def save(self, path: str) -> None:
        """Synopsis partitioned by band and clustered by label and cell key; boxes by delta."""
        self.synopsis.repartition("band", "label").sortWithinPartitions("label", F.desc("cell_key")).write.mode("overwrite").partitionBy("band").parquet(f"{path}/synopsis")
        self.boxes.repartition("delta", "label").sortWithinPartitions("label", "v").write.mode("overwrite").partitionBy("delta").parquet(f"{path}/boxes")
        self.bands.coalesce(1).write.mode("overwrite").parquet(f"{path}/bands")
        self.star.write.mode("overwrite").parquet(f"{path}/star")

    @classmethod
    def load(cls, spark, path: str, g: Graph, p: BuildParams) -> Index:
        out = cls.__new__(cls)
        out.graph, out.params, out.t = g, p, None
        out.synopsis, out.boxes, out.bands, out.star = (spark.read.parquet(f"{path}/{x}") for x in ("synopsis", "boxes", "bands", "star"))
        return out


class Part(Index):
    """The rows of touched vertices (see ``Index.changed``)."""

    def __init__(self, old: Index, vertices: DataFrame, signed: DataFrame, t: DataFrame):
        super().__init__(Graph(vertices, old.graph.edge_life, name=old.graph.name), old.params, old.deltas)
        self.old, self.signed, self.touched = old, signed, t

    @cached_property
    def bands(self) -> DataFrame:
        return self.old.bands

    @cached_property
    def grid(self) -> DataFrame:
        return self.old.grid

    @cached_property
    def hist(self) -> DataFrame:
        return materialise(add_counts(self.old.hist.join(self.touched, "v", "left_semi"), self.signed), "hist-touched")

    @cached_property
    def star(self) -> DataFrame:
        p, d = self.params, self.dictionary
        sums = [f"ns{k}" for k in range(p.d)]
        own = self.graph.vertices.join(self.touched, "v", "left_semi").select("v", "label")
        star = own.join(neighbour_sums(self.hist, d, p), "v", "left").fillna(0, ["deg", *sums]).join(F.broadcast(d), "label")
        return materialise(star.select("v", "label", "deg", *sums, *embedding_columns(p)), "star-touched")

    @cached_property
    def synopsis(self) -> DataFrame:
        return place_in_grid(self.corners, self.grid, self.params)


class Merged(Index):
    """An index's rows beside those of touched vertices: an epoch writes the latter only, and the tables are written
    anew when ``PIECES`` epochs stand beside them."""

    def __init__(self, old: Index, part: Part):
        super().__init__(part.graph, part.params, part.deltas)
        self.old, self.part, self.touched, self.depth = old, part, part.touched, old.depth + 1

    @cached_property
    def bands(self) -> DataFrame:
        return self.old.bands

    @cached_property
    def grid(self) -> DataFrame:
        return self.old.grid

    def _carried(self, name: str) -> DataFrame:
        old, new = getattr(self.old, name), getattr(self.part, name)
        both = old.join(self.touched, "v", "left_anti").unionByName(new.select(*old.columns))
        return materialise(both, name) if self.depth % PIECES == 0 else both

    @cached_property
    def hist(self) -> DataFrame:
        return self._carried("hist")

    @cached_property
    def star(self) -> DataFrame:
        return self._carried("star")

    @cached_property
    def corners(self) -> DataFrame:
        return self._carried("corners")

    @cached_property
    def boxes(self) -> DataFrame:
        return self._carried("boxes")

    @cached_property
    def synopsis(self) -> DataFrame:
        return self._carried("synopsis")


def touched(ops: DataFrame) -> DataFrame:
    """The ends of updated edges, one row each."""
    return ops.select(F.explode(F.array("u", "v")).alias("v")).distinct()


def synopsis_space(star: DataFrame, p: BuildParams) -> DataFrame:
    """Scalars by the space formula: 2d per vertex and 5d per unit of degree (4d of boxes, d of
    lists), beside what is stored here: boxes for wanted degrees and label runs."""
    return star.agg((F.count(F.lit(1)) * 2 * p.d).alias("vector_scalars"), (F.sum("deg") * 5 * p.d).alias("box_and_list_scalars"))
