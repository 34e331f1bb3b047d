"""Data graphs: simple undirected edges, and arcs whose vertex keys carry the vertex order.

A vertex key is (order value << 40) | id: comparing keys compares vertices in the chosen strict order
(ascending degree, ties by id), and no table ever needs a rank column or a lookup. Ids are below 2^40,
order values below 2^23; degrees beyond that tie and are ordered by id, which is still a strict order.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from huecount.functions import signature as sg
from huecount.session import cut

ID_BITS = 40
MAX_ORDER = (1 << 23) - 1
#: Arcs that may be sent to every task as rows, some 50 bytes each.
FEW_ARCS = 1 << 20
#: Arcs that may be sent to every task as lists of neighbours, 8 bytes each, and how many of them at once.
MOST_NEAR, NEAR_LOT = 1 << 24, 1 << 22
#: Candidates that one task sums in place, in the mean, and parts at most.
PART_CANDIDATES, MOST_PARTS = 1 << 20, 4096


def key_of(order_value: Column, v: Column) -> Column:
    fits = (v >= 0) & (v < 1 << ID_BITS)
    v = F.when(fits, v).otherwise(F.raise_error(F.concat(F.lit("vertex ids lie in 0 to 2^40 - 1, not "), v.cast("string"))).cast("long"))
    return F.shiftleft(F.least(order_value, F.lit(MAX_ORDER)).cast("long"), ID_BITS).bitwiseOR(v)


def id_of(key: Column) -> Column:
    return key.bitwiseAND(F.lit((1 << ID_BITS) - 1))


def order_of(key: Column) -> Column:
    """The order value in a key: the degree, under the order by degree."""
    return F.call_function("shiftright", key, F.lit(ID_BITS))


def simple_edges(pairs: DataFrame) -> DataFrame:
    """src < dst, distinct, without loops or nulls, from any pairs (src, dst)."""
    kept = pairs.where("src is not null and dst is not null and src <> dst")
    return kept.select(F.least("src", "dst").cast("long").alias("src"), F.greatest("src", "dst").cast("long").alias("dst")).distinct()


def both_ways(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


@dataclass
class DataGraph:
    name: str
    edges: DataFrame
    order: str = "degree"
    bipartite: bool = False
    _arcs: DataFrame | None = field(default=None, repr=False)
    _largest: int | None = field(default=None, repr=False)
    _flat: int | None = field(default=None, repr=False)
    _work: dict | None = field(default=None, repr=False)
    _near: dict = field(default_factory=dict, repr=False)
    _lists: DataFrame | None = field(default=None, repr=False)
    told: dict = field(default_factory=dict, repr=False)  # loads that are known, by colouring and order
    sides: bool = False  # bipartite, and the lowest bit of an id tells the side

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    def degrees(self) -> DataFrame:
        """v, deg."""
        return both_ways(self.edges).groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg"))

    def vertex_keys(self) -> DataFrame:
        """v, deg, key."""
        if self.order == "degree":
            value = F.col("deg")
        elif self.order == "id":
            value = F.lit(0)
        elif self.order == "random":
            value = F.pmod(F.xxhash64("v", F.lit(20240101)), F.lit(MAX_ORDER))
        else:
            raise ValueError(f"no vertex order {self.order!r}")
        return self.degrees().withColumn("key", key_of(value, F.col("v")))

    def with_order(self, order: str) -> DataGraph:
        return DataGraph(self.name, self.edges, order, self.bipartite)

    def arcs(self) -> DataFrame:
        """src, dst as keys, both directions; made once, partitioned by src."""
        if self._arcs is None:
            self.edges = cut(self.edges, "edges")  # read for degrees and by both joins
            keys = self.vertex_keys().select("v", "key")
            a = keys.select(F.col("v").alias("src"), F.col("key").alias("a"))
            b = keys.select(F.col("v").alias("dst"), F.col("key").alias("b"))
            one_way = self.edges.join(a, "src").join(b, "dst").select(F.col("a").alias("src"), F.col("b").alias("dst"))
            self._arcs = cut(both_ways(one_way), "arcs", ("src",))
        return self._arcs

    def largest_order(self) -> int:
        """The largest degree, if keys are ordered by degree, else 0."""
        if self._largest is None:
            top = self.arcs().agg(F.max(order_of(F.col("src")))).first()[0] if self.order == "degree" else 0
            self._largest = int(top or 0)
        return self._largest

    def work(self) -> dict:
        """arcs, and candidates of one step from every arc (plain), from arcs that start at their higher end (high), and from arcs that
        start on either side (0, 1)."""
        if self._work is None:
            deg, side = order_of(F.col("dst")), F.col("src").bitwiseAND(1)
            sums = {"plain": F.sum(deg), "high": F.sum(F.when(F.col("src") > F.col("dst"), deg)), "0": F.sum(F.when(side == 0, deg)), "1": F.sum(F.when(side == 1, deg))}
            row = self.arcs().agg(F.count("*").alias("arcs"), *[x.alias(k) for k, x in sums.items()]).first()
            self._work = {k: int(x or 0) for k, x in row.asDict().items()}
        return self._work

    def flat_parts(self, trials: int = 1, of: str = "plain") -> int:
        """In how many parts paths may be dealt by their start while arcs go to every task, or 0: arcs are few enough for that, and no
        vertex has more than a part's share of them. More parts where a step has more candidates (of: as in work)."""
        if self._flat is None:
            n, top = self.work()["arcs"], self.largest_order()
            parts = max(4 * self.spark.sparkContext.defaultParallelism, int(self.spark.conf.get("spark.sql.shuffle.partitions")))
            self._flat = parts if self.order == "degree" and 0 < n <= MOST_NEAR and top * parts <= 2 * n else 0
        return self._flat and max(self._flat, min(MOST_PARTS, self.work()[of] * trials // PART_CANDIDATES))

    def lists(self) -> DataFrame:
        """tail, near: the neighbours of every vertex, written once."""
        if self._lists is None:
            self._lists = cut(self.arcs().groupBy(F.col("src").alias("tail")).agg(F.collect_list("dst").alias("near")), "lists")
        return self._lists

    def near(self, coloring=None) -> list[DataFrame]:
        """tail, near (its neighbours) of all vertices, in lots of NEAR_LOT arcs or so, for flat graphs. With a colouring near has a
        list for every colour of trial 0: bw (its bit), ws."""
        kept = repr(coloring)
        if kept not in self._near:
            lots = max(1, -(-self.work()["arcs"] // NEAR_LOT))
            tail = F.col("src").alias("tail")
            if coloring is None:
                lists = self.arcs().groupBy(tail).agg(F.collect_list("dst").alias("near"))
            else:
                hues = self.arcs().groupBy(tail, sg.bit(coloring.color(id_of(F.col("dst")), F.lit(0))).alias("bw")).agg(F.collect_list("dst").alias("ws"))
                lists = hues.groupBy("tail").agg(F.collect_list(F.struct("bw", "ws")).alias("near"))
            lists = cut(lists.withColumn("lot", F.pmod(F.xxhash64("tail"), F.lit(lots))), "near")
            self._near[kept] = [lists.where(F.col("lot") == i).select("tail", "near") for i in range(lots)]
        return self._near[kept]

    def save_bucketed(self, table: str, buckets: int = 64) -> None:
        """Arcs as a bucketed, sorted table: later extensions move only the path table."""
        self.arcs().write.mode("overwrite").bucketBy(buckets, "src").sortBy("src", "dst").saveAsTable(table)

    @classmethod
    def from_bucketed(cls, spark: SparkSession, table: str, name: str = "bucketed") -> DataGraph:
        arcs = spark.table(table)
        edges = arcs.where("src < dst").select(id_of(F.col("src")).alias("src"), id_of(F.col("dst")).alias("dst"))
        return cls(name, simple_edges(edges), _arcs=arcs)


def profile(g: DataGraph) -> DataFrame:
    """view, nodes, edges, avg_deg (edges over nodes), max_deg."""
    return g.degrees().agg(
        F.lit(g.name).alias("view"),
        F.count("*").alias("nodes"),
        (F.sum("deg") / 2).cast("long").alias("edges"),
        (F.sum("deg") / 2 / F.count("*")).alias("avg_deg"),
        F.max("deg").alias("max_deg"),
    )


def dense_rank(g: DataGraph, partitions: int | None = None) -> DataFrame:
    """v, deg, rank (0-based position by degree, then id) without a window over everything: ranges of the
    order are counted, and each range numbers its own rows."""
    rows = g.degrees()
    n = partitions or max(2, g.spark.sparkContext.defaultParallelism)
    dealt = cut(rows.repartitionByRange(n, "deg", "v").withColumn("part", F.spark_partition_id()), "ranges")
    sizes = dealt.groupBy("part").count()  # one row a range
    before = F.sum("count").over(W.orderBy("part")) - F.col("count")
    offsets = sizes.select("part", before.alias("before"))
    inside = F.row_number().over(W.partitionBy("part").orderBy("deg", "v")) - 1
    return dealt.withColumn("inside", inside).join(F.broadcast(offsets), "part").select("v", "deg", (F.col("before") + F.col("inside")).alias("rank"))


def prune(g: DataGraph, least_degree: int, rounds: int = 2) -> DataGraph:
    """Drop vertices of a degree below least_degree, a number of rounds. For a query without leaves 2 is
    safe, since every image of a query node has at least that node's degree within the match."""
    edges = g.edges
    for _ in range(rounds):
        way = both_ways(edges)
        alive = way.groupBy("src").count().where(F.col("count") >= least_degree).select(F.col("src").alias("v"))
        edges = edges.join(alive, edges["src"] == alive["v"], "left_semi")
        edges = edges.join(alive, edges["dst"] == alive["v"], "left_semi")
        edges = cut(edges, "pruned")
    return DataGraph(g.name, edges, g.order, g.bipartite)
