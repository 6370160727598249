"""Edge lists: one row per undirected edge with src < dst, and the vertices they join."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.coins import coin
from ..plans.spool import cut, cut_and_count

TAG = 1 << 40  # typed vertices: tag * TAG + key


@dataclass
class EdgeSet:
    vertices: DataFrame  # vid
    edges: DataFrame  # src, dst, and weight if there are weights
    listed: DataFrame | None = None  # vid: vertices known beside the ends of edges; only of graphs whose vertices follow from both
    settled: bool = False  # both tables are written

    @property
    def n(self) -> int:
        if not hasattr(self, "_n"):
            self._n = self.vertices.count()
        return self._n

    def settle(self) -> EdgeSet:
        """The same graph with both tables written once, so that passes over the edges don't derive them again."""
        if self.settled:
            return self
        if not hasattr(self, "_written"):
            edges = cut(self.edges)
            vertices = self.vertices if self.listed is None else _ends(edges, self.listed)
            vertices, n = cut_and_count(vertices)
            self._written = EdgeSet(vertices, edges, settled=True)
            self._written._n = n
        return self._written


def _ends(edges: DataFrame, listed: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("vid")).union(listed).distinct()


def canonical_edges(df: DataFrame, a: str = "src", b: str = "dst", weight: str | None = None) -> DataFrame:
    """Ends in order; nulls, loops and copies dropped; the least weight of copies kept."""
    ends = df.where(f"{a} IS NOT NULL AND {b} IS NOT NULL AND {a} <> {b}").select(F.least(a, b).cast("long").alias("src"), F.greatest(a, b).cast("long").alias("dst"), *([F.col(weight).alias("weight")] if weight else []))
    return ends.groupBy("src", "dst").agg(F.min("weight").alias("weight")) if weight else ends.distinct()


def build(edges: DataFrame, vertices: DataFrame | None = None, weight: str | None = None) -> EdgeSet:
    own = canonical_edges(edges, weight=weight)
    listed = own.select(F.col("src").alias("vid")).where("false") if vertices is None else vertices.select(F.col("vid").cast("long"))
    return EdgeSet(_ends(own, listed), own, listed)


def validate_edges(g: EdgeSet) -> DataFrame:
    """Counts of what a clean edge set has none of."""
    e, v = g.edges, g.vertices
    rows = e.agg(F.count_if(F.col("src").isNull() | F.col("dst").isNull()).alias("nulls"), F.count_if(F.col("src") == F.col("dst")).alias("loops"), F.count_if(F.col("src") > F.col("dst")).alias("disordered"))
    copies = e.groupBy("src", "dst").count().where("count > 1").agg(F.count(F.lit(1)).alias("copies"))
    dangling = e.select(F.explode(F.array("src", "dst")).alias("vid")).join(v, "vid", "left_anti").agg(F.count(F.lit(1)).alias("dangling"))
    return rows.join(copies).join(dangling)


def symmetrize(edges: DataFrame) -> DataFrame:
    """Both directions of every edge, in one scan, with the edge itself as e_src, e_dst."""
    extra = [c for c in edges.columns if c not in ("src", "dst")]
    both = F.explode(F.array(F.struct(F.col("src").alias("u"), F.col("dst").alias("v")), F.struct(F.col("dst").alias("u"), F.col("src").alias("v"))))
    return edges.select(both.alias("x"), F.col("src").alias("e_src"), F.col("dst").alias("e_dst"), *extra).select("x.u", "x.v", "e_src", "e_dst", *extra)


def degrees(g: EdgeSet) -> DataFrame:
    """vid, d; isolated vertices have 0."""
    d = symmetrize(g.edges).groupBy("u").agg(F.count(F.lit(1)).alias("d"))
    return g.vertices.join(d, F.col("vid") == F.col("u"), "left").select("vid", F.coalesce("d", F.lit(0)).cast("long").alias("d"))


def component_degrees(labels: DataFrame, deg: DataFrame) -> DataFrame:
    """comp, cdeg: the largest original degree of a component's members."""
    return labels.join(deg, "vid").groupBy("comp").agg(F.max("d").alias("cdeg"))


def labelled(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """The edges with comp_src and comp_dst."""
    a = labels.select(F.col("vid").alias("src"), F.col("comp").alias("comp_src"))
    b = labels.select(F.col("vid").alias("dst"), F.col("comp").alias("comp_dst"))
    return edges.join(a, "src").join(b, "dst")


def crossing_edges(edges: DataFrame, labels: DataFrame) -> DataFrame:
    return labelled(edges, labels).where("comp_src <> comp_dst")


def internal_edges(edges: DataFrame, labels: DataFrame) -> DataFrame:
    return labelled(edges, labels).where("comp_src = comp_dst")


def growable(labels: DataFrame, edges: DataFrame) -> DataFrame:
    """comp of the components that an edge leaves."""
    return crossing_edges(edges, labels).select(F.explode(F.array("comp_src", "comp_dst")).alias("comp")).distinct()


def induced_subgraph(g: EdgeSet, vids: DataFrame) -> EdgeSet:
    e = g.edges.join(vids.select(F.col("vid").alias("src")), "src", "left_semi").join(vids.select(F.col("vid").alias("dst")), "dst", "left_semi")
    return EdgeSet(g.vertices.join(vids, "vid", "left_semi"), e)


def relabel(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """The graph contracted to components: one edge (cu < cv) a pair, with its least original edge."""
    c = crossing_edges(edges, labels)
    best = ["src", "dst"] if "weight" not in edges.columns else ["weight", "src", "dst"]
    return c.groupBy(F.least("comp_src", "comp_dst").alias("cu"), F.greatest("comp_src", "comp_dst").alias("cv")).agg(F.min(F.struct(*best)).alias("e"))


def weight_between(edges: DataFrame, low: float, high: float) -> DataFrame:
    return edges.where(F.col("weight").between(low, high))


def edges_up_to(edges: DataFrame, instance: int) -> DataFrame:
    return edges.where(F.col("first_instance") <= instance)


def disjoint_union(instances: DataFrame, vertices: DataFrame, count: int) -> EdgeSet:
    """Graphs of one vertex set side by side.  instances: instance, src, dst.  Ids become instance * TAG * 64 + vid."""
    shift = F.col("instance").cast("long") * F.lit(TAG * 64)
    e = instances.select((F.col("src") + shift).alias("src"), (F.col("dst") + shift).alias("dst"), "instance")
    v = vertices.select(F.explode(F.sequence(F.lit(1), F.lit(count))).alias("instance"), "vid").select((F.col("vid") + shift).alias("vid"))
    return EdgeSet(v, e.select("src", "dst"))


def generate_graph(spark, kind: str, n: int, seed: int = 0) -> EdgeSet:
    """Planted graphs: path, cycle, star, complete, grid, tree, sparse, hubs (n copies of the four-hub gadget)."""
    ids = spark.range(n).select(F.col("id").alias("vid"))
    if kind == "path":
        e = spark.range(max(n - 1, 0)).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    elif kind == "cycle":
        e = spark.range(n).select(F.col("id").alias("src"), ((F.col("id") + 1) % n).alias("dst"))
    elif kind == "star":
        e = spark.range(1, n).select(F.lit(0).cast("long").alias("src"), F.col("id").alias("dst"))
    elif kind == "complete":
        e = spark.range(n).select(F.col("id").alias("src"), F.explode(F.sequence(F.col("id"), F.lit(n - 1).cast("long"))).alias("dst"))
    elif kind == "grid":
        w = max(1, int(n**0.5))
        right = spark.range(n).where((F.col("id") % w < w - 1) & (F.col("id") + 1 < n)).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
        e = right.union(spark.range(n).where(F.col("id") + w < n).select(F.col("id").alias("src"), (F.col("id") + w).alias("dst")))
    elif kind == "tree":
        e = spark.range(1, n).select(F.floor(coin(seed, "tree", "id") * F.col("id")).cast("long").alias("src"), F.col("id").alias("dst"))
    elif kind == "sparse":  # components of 1 to 6 vertices
        e = spark.range(1, n).where((F.col("id") % 7 != 0) & (coin(seed, "sparse", "id") < 0.8)).select((F.col("id") - 1).alias("src"), F.col("id").alias("dst"))
    elif kind == "hubs":
        return hub_gadget(spark, n)
    else:
        raise ValueError(kind)
    return build(e, ids)


def hub_gadget(spark, copies: int) -> EdgeSet:
    """Stars A, B with 7 leaves and C, D with 9; a0-c0, a0-b0, b0-d0; the next copy's a1 joins this copy's b1."""
    base = F.col("id") * 36
    hub = {"a": 0, "b": 8, "c": 16, "d": 26}
    pairs = [(hub[k], hub[k] + 1 + i) for k, m in (("a", 7), ("b", 7), ("c", 9), ("d", 9)) for i in range(m)]
    pairs += [(hub["a"] + 1, hub["c"] + 1), (hub["a"] + 1, hub["b"] + 1), (hub["b"] + 1, hub["d"] + 1)]
    own = spark.range(copies).select(F.explode(F.array(*(F.struct((base + x).alias("src"), (base + y).alias("dst")) for x, y in pairs))).alias("e")).select("e.*")
    chain = spark.range(max(copies - 1, 0)).select((base + 36 + hub["a"] + 2).alias("src"), (base + hub["b"] + 2).alias("dst"))
    return build(own.union(chain))
