"""Ten graph views of the given tables, as DataFrames and as SQL text for DuckDB."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from huecount.operators.graph import DataGraph, simple_edges

TABLES = tuple("region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split())
# Fixed vertex kinds of the supply chain: id = 8 * key + kind.
CUSTOMER, ORDER, PART, SUPPLIER, NATION, REGION = range(6)
WORD = "[a-zà-ÿ]+"
HREF = 'href="([^"]+)"'
NEIGHBOURS = 8


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _pairs(df: DataFrame, a, b) -> DataFrame:
    return df.select(a.cast("long").alias("src"), b.cast("long").alias("dst"))


def _kind(column: str, kind: int):
    return F.col(column) * 8 + kind


def supply_chain(spark: SparkSession, d: str) -> DataFrame:
    t = lambda n: table(spark, d, n)
    o, li, c, s, n = t("orders"), t("lineitem"), t("customer"), t("supplier"), t("nation")
    parts = [
        _pairs(o, _kind("o_orderkey", ORDER), _kind("o_custkey", CUSTOMER)),
        _pairs(li, _kind("l_orderkey", ORDER), _kind("l_partkey", PART)),
        _pairs(li, _kind("l_orderkey", ORDER), _kind("l_suppkey", SUPPLIER)),
        _pairs(li, _kind("l_partkey", PART), _kind("l_suppkey", SUPPLIER)),
        _pairs(c, _kind("c_custkey", CUSTOMER), _kind("c_nationkey", NATION)),
        _pairs(s, _kind("s_suppkey", SUPPLIER), _kind("s_nationkey", NATION)),
        _pairs(n, _kind("n_nationkey", NATION), _kind("n_regionkey", REGION)),
    ]
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.union(p)
    return whole


def _dense_ids(strings: DataFrame, column: str) -> DataFrame:
    """column, id: position in binary order, by ranges instead of one window."""
    distinct = strings.select(column).distinct()
    dealt = distinct.repartitionByRange(max(2, strings.sparkSession.sparkContext.defaultParallelism), column)
    from huecount.session import cut

    parts = cut(dealt.withColumn("part", F.spark_partition_id()), "ids")
    before = F.sum("count").over(W.orderBy("part")) - F.col("count")
    offsets = parts.groupBy("part").count().select("part", before.alias("before"))
    inside = F.row_number().over(W.partitionBy("part").orderBy(column))
    return parts.withColumn("inside", inside).join(F.broadcast(offsets), "part").select(column, (F.col("before") + F.col("inside")).alias("id"))


def word_adj(spark: SparkSession, d: str) -> DataFrame:
    words = F.regexp_extract_all(F.lower("text"), F.lit(WORD), F.lit(0))
    n = F.greatest(F.size("w") - 1, F.lit(0))
    steps = F.arrays_zip(F.slice("w", F.lit(1), n).alias("a"), F.slice("w", F.lit(2), n).alias("b"))
    pairs = table(spark, d, "documents").select(words.alias("w")).select(F.explode(steps).alias("p")).select(F.col("p.a").alias("a"), F.col("p.b").alias("b"))
    pairs = pairs.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    ids = _dense_ids(table(spark, d, "documents").select(F.explode(words).alias("word")), "word")
    a, b = ids.select(F.col("word").alias("a"), F.col("id").alias("src")), ids.select(F.col("word").alias("b"), F.col("id").alias("dst"))
    return pairs.join(a, "a").join(b, "b").select("src", "dst")


def copurchase(spark: SparkSession, d: str) -> DataFrame:
    items = table(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    x, y = items.select("l_orderkey", F.col("l_partkey").alias("src")), items.select("l_orderkey", F.col("l_partkey").alias("dst"))
    return x.join(y, "l_orderkey").where("src < dst").select("src", "dst")


def _bipartite(df: DataFrame, left, right) -> DataFrame:
    return _pairs(df, left * 2, right * 2 + 1)


def part_supplier(spark: SparkSession, d: str) -> DataFrame:
    return _bipartite(table(spark, d, "lineitem"), F.col("l_partkey"), F.col("l_suppkey"))


def order_part(spark: SparkSession, d: str) -> DataFrame:
    return _bipartite(table(spark, d, "lineitem"), F.col("l_orderkey"), F.col("l_partkey"))


def customer_part(spark: SparkSession, d: str) -> DataFrame:
    o, li = table(spark, d, "orders"), table(spark, d, "lineitem")
    return _bipartite(o.join(li, o["o_orderkey"] == li["l_orderkey"]), F.col("o_custkey"), F.col("l_partkey"))


def user_hour(spark: SparkSession, d: str) -> DataFrame:
    hour = F.expr("timestampdiff(HOUR, timestamp_ntz'2024-01-01 00:00:00', ts)")
    return _bipartite(table(spark, d, "events"), F.col("user_id"), hour)


def succession(spark: SparkSession, d: str, salt_hours: int = 24) -> DataFrame:
    """Users of consecutive events. Time ranges follow each other; the last event of a range is handed to
    the next one, so no window spans everything."""
    e = table(spark, d, "events").select("ts", "event_id", "user_id").withColumn("slot", F.expr(f"timestampdiff(HOUR, timestamp_ntz'2024-01-01 00:00:00', ts) div {salt_hours}"))
    nxt = F.lead("user_id").over(W.partitionBy("slot").orderBy("ts", "event_id"))
    inner = e.withColumn("next", nxt).where("next is not null").select(F.col("user_id").alias("src"), F.col("next").alias("dst"))
    ends = e.groupBy("slot").agg(F.max_by("user_id", F.struct("ts", "event_id")).alias("last"), F.min_by("user_id", F.struct("ts", "event_id")).alias("first"))
    across = ends.withColumn("next", F.lead("first").over(W.orderBy("slot"))).where("next is not null").select(F.col("last").alias("src"), F.col("next").alias("dst"))
    return inner.union(across)


def page_anchor(spark: SparkSession, d: str) -> DataFrame:
    p = table(spark, d, "pages").select(F.concat(F.lit("p:"), F.col("page_id").cast("string")).alias("p"), F.explode(F.regexp_extract_all("html", F.lit(HREF), F.lit(1))).alias("href"))
    p = p.select("p", F.concat(F.lit("t:"), F.col("href")).alias("t")).distinct()
    ids = _dense_ids(p.select(F.col("p").alias("name")).union(p.select("t")), "name")
    a, b = ids.select(F.col("name").alias("p"), F.col("id").alias("src")), ids.select(F.col("name").alias("t"), F.col("id").alias("dst"))
    return p.join(a, "p").join(b, "t").select("src", "dst")


def knn8(spark: SparkSession, d: str, k: int = NEIGHBOURS, block: int = 2048) -> DataFrame:
    """Symmetrised nearest neighbours by cosine, ties to the smaller id; vectors meet block by block and
    only k neighbours of a vector leave a block. Vectors without a direction (null, zero, or holding a null or NaN)
    take no part."""
    import numpy as np
    import pandas as pd

    sound = ~F.exists("embedding", lambda c: c.isNull() | F.isnan(c)) & F.exists("embedding", lambda c: c != 0)
    v = table(spark, d, "embeddings").where("vec_id is not null and embedding is not null").where(sound).select("vec_id", "embedding")
    n = v.count()
    blocks = max(1, -(-n // block))
    dealt = v.withColumn("own", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))

    def pack(rows: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(rows["embedding"].to_numpy()).astype(np.float64)
        x /= np.sqrt((x * x).sum(axis=1, keepdims=True))
        return pd.DataFrame({"own": [rows["own"].iat[0]], "ids": [rows["vec_id"].to_numpy(np.int64).tobytes()], "x": [x.tobytes()], "dim": [x.shape[1]]})

    packed = dealt.groupBy("own").applyInPandas(pack, "own int, ids binary, x binary, dim int")
    left = packed.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    right = packed.select(F.col("own").alias("other"), F.col("ids").alias("ids2"), F.col("x").alias("x2"))

    def meet(batches):
        for batch in batches:
            for r in batch.itertuples():
                a, b = np.frombuffer(r.ids, np.int64), np.frombuffer(r.ids2, np.int64)
                order = np.argsort(b)
                score = np.round(np.frombuffer(r.x).reshape(-1, r.dim) @ np.frombuffer(r.x2).reshape(-1, r.dim)[order].T, 9)
                b, out = b[order], []
                for i in range(len(a)):
                    score[i, b == a[i]] = -9
                    top = np.argsort(-score[i], kind="stable")[: k + 1]
                    out += [(a[i], b[j], score[i, j]) for j in top if b[j] != a[i]]
                yield pd.DataFrame(out, columns=["src", "dst", "score"])

    near = left.join(right, "other").select("ids", "x", "ids2", "x2", "dim").mapInPandas(meet, "src long, dst long, score double")
    rank = F.row_number().over(W.partitionBy("src").orderBy(F.desc("score"), "dst"))
    return near.withColumn("rank", rank).where(F.col("rank") <= k).select("src", "dst")


VIEWS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (supply_chain, word_adj, copurchase, part_supplier, order_part, customer_part, user_hour, succession, page_anchor, knn8)
}
#: Their ids tell the side by the lowest bit.
SIDED = frozenset(("part_supplier", "order_part", "customer_part", "user_hour"))
BIPARTITE = frozenset(("part_supplier", "order_part", "customer_part", "user_hour", "page_anchor"))


def graph_view(spark: SparkSession, sf_dir: str, name: str) -> DataGraph:
    return DataGraph(name, simple_edges(VIEWS[name](spark, sf_dir)), bipartite=name in BIPARTITE, sides=name in SIDED)


_SIMPLE = "SELECT DISTINCT least(a, b)::BIGINT AS src, greatest(a, b)::BIGINT AS dst FROM ({}) WHERE a <> b"
_RAW_SQL = {
    "supply_chain": """SELECT 8*o_orderkey+1 AS a, 8*o_custkey AS b FROM orders UNION ALL SELECT 8*l_orderkey+1, 8*l_partkey+2 FROM lineitem
        UNION ALL SELECT 8*l_orderkey+1, 8*l_suppkey+3 FROM lineitem UNION ALL SELECT 8*l_partkey+2, 8*l_suppkey+3 FROM lineitem
        UNION ALL SELECT 8*c_custkey, 8*c_nationkey+4 FROM customer UNION ALL SELECT 8*s_suppkey+3, 8*s_nationkey+4 FROM supplier
        UNION ALL SELECT 8*n_nationkey+4, 8*n_regionkey+5 FROM nation""",
    "copurchase": "SELECT x.l_partkey AS a, y.l_partkey AS b FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey",
    "part_supplier": "SELECT 2*l_partkey AS a, 2*l_suppkey+1 AS b FROM lineitem",
    "order_part": "SELECT 2*l_orderkey AS a, 2*l_partkey+1 AS b FROM lineitem",
    "customer_part": "SELECT 2*o_custkey AS a, 2*l_partkey+1 AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "user_hour": "SELECT 2*user_id AS a, 2*date_diff('hour', timestamp '2024-01-01', ts)+1 AS b FROM events",
    "succession": "SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b FROM events",
    "word_adj": f"""SELECT x.id AS a, y.id AS b FROM (SELECT w[i] AS wa, w[i+1] AS wb FROM (SELECT w, unnest(range(1, len(w))) AS i FROM
        (SELECT regexp_extract_all(lower(text), '{WORD}') AS w FROM documents))) p
        JOIN (SELECT word, row_number() OVER (ORDER BY word) AS id FROM (SELECT DISTINCT unnest(regexp_extract_all(lower(text), '{WORD}')) AS word FROM documents)) x ON x.word = wa
        JOIN (SELECT word, row_number() OVER (ORDER BY word) AS id FROM (SELECT DISTINCT unnest(regexp_extract_all(lower(text), '{WORD}')) AS word FROM documents)) y ON y.word = wb""",
    "page_anchor": f"""WITH l AS (SELECT DISTINCT 'p:' || page_id AS p, 't:' || unnest(regexp_extract_all(html, '{HREF}', 1)) AS t FROM pages),
        i AS (SELECT name, row_number() OVER (ORDER BY name) AS id FROM (SELECT p AS name FROM l UNION SELECT t FROM l))
        SELECT x.id AS a, y.id AS b FROM l JOIN i x ON x.name = p JOIN i y ON y.name = t""",
    "knn8": f"""WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings),
        s AS (SELECT x.vec_id AS a, y.vec_id AS b, round(list_inner_product(x.e, y.e) / sqrt(list_inner_product(x.e, x.e)) / sqrt(list_inner_product(y.e, y.e)), 9) AS c FROM v x JOIN v y ON x.vec_id <> y.vec_id)
        SELECT a, b FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY c DESC, b) AS r FROM s) WHERE r <= {NEIGHBOURS}""",
}
VIEW_SQL = {name: _SIMPLE.format(raw) for name, raw in _RAW_SQL.items()}
