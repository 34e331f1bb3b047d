"""Exact top-k inner products, norm-sorted, with partial sums in a rotated basis.

Candidates lie in groups by descending length. The right singular vectors of all candidates (from their
Gram matrix, a sum over partitions) rotate both sides, so that the first coordinates carry most of every
product. A query visits candidates from the longest to the shortest. It stops when the length of a
candidate times its own cannot reach its k-th best score; for others it adds up the first coordinates and
drops a candidate as soon as partial sum plus the product of what is left of both lengths
(Cauchy-Schwarz) is below that score. Survivors are scored exactly, in integers.

Queries and candidates meet in blocks. The k-th best scores of a block's queries within the head group of the longest
candidates (a fixed number of rows) are known first, and give the least length that a candidate of any of its
queries must have: the block travels only to groups of candidates from bands that reach it.
Candidates move once, dealt to sets of groups; each set answers with k rows a query at most, which reach what the query
knows to have, and a ranked window cuts them to k.

Defined results: vectors that are null or empty, or hold a null, NaN or infinite component, take no part; nor do
those that differ in dimension from most (of dimensions as frequent, the larger), for they have no inner product with them; repeated vec_ids are candidates each, except of their own id;
ties go to the smaller vec_id; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from huecount.llm.common import cut

K = 5
SCALE = 256
QUERY_BLOCK = 512
CANDIDATE_GROUP = 8192
HEAD = 4096
BANDS = 64
#: Candidates that a meeting looks at in one go.
STEP = 1024
#: Sets of groups that candidates are dealt to, at least, as far as there are groups; groups of a set and query blocks of a lot, at most.
SETS, SET_GROUPS, LOT_BLOCKS = 64, 32, 1024
#: Coordinates after which a query's candidates are pruned, as shares of the dimension.
STAGES = (0.25, 0.5)


def scaled(rows: DataFrame, scale: int = SCALE) -> DataFrame:
    """vec_id, v (double array of whole numbers), norm of the vectors that take part."""
    x = F.transform("embedding", lambda c: c.cast("double"))
    good = F.col("embedding").isNotNull() & ~F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf")))
    v = rows.where(good & F.col("vec_id").isNotNull()).select("vec_id", F.transform(x, lambda c: F.floor(c * scale).cast("double")).alias("v"))
    return v.withColumn("norm", F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, c: a + c * c)))


def rotation(vectors: DataFrame, dim: int) -> np.ndarray:
    """Right singular vectors of all vectors, strongest first, from partial Gram matrices of partitions."""

    def gram(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total = np.zeros((dim, dim))
        for batch in batches:
            if len(batch):
                x = np.stack(batch["v"].to_numpy())
                total += x.T @ x
        yield pd.DataFrame({"i": np.arange(dim * dim), "g": total.ravel()})

    cells = vectors.select("v").mapInPandas(gram, "i int, g double").groupBy("i").agg(F.sum("g").alias("g")).toPandas()  # dim * dim rows
    if not len(cells):
        return np.eye(dim)
    g = np.zeros(dim * dim)
    g[cells["i"]] = cells["g"]
    _, basis = np.linalg.eigh(g.reshape(dim, dim))
    return basis[:, ::-1].copy()


class Side:
    """Whole vectors, longest first or in any order, with what every meeting needs of them: lengths, coordinates in the rotated
    basis, and lengths of what is left after each of the first cuts."""

    def __init__(self, x: np.ndarray, ids: np.ndarray, basis: np.ndarray):
        self.x, self.ids, self.turned = x, ids, x @ basis
        self.norm = np.sqrt((x * x).sum(axis=1))
        self.cuts = [max(1, int(x.shape[1] * s)) for s in STAGES]
        self.rest = [np.sqrt(np.maximum((self.turned[:, n:] ** 2).sum(axis=1), 0)) for n in self.cuts]
        self._light: tuple[np.ndarray, np.ndarray] | None = None

    def light(self) -> tuple[np.ndarray, np.ndarray]:
        """The vectors and their rotated coordinates in single precision."""
        if self._light is None:
            self._light = self.x.astype(np.float32), self.turned.astype(np.float32)
        return self._light


def meet(q: Side, floor: np.ndarray, c: Side, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """Number of the query, vec_id and score of the k best candidates of each query, by query and rank, as far as they
    reach its floor, and how many products were finished. c: longest first. While the product of two lengths is below 2^24 all sums
    of whole numbers are exact in single precision; from 2^53 on they are made in integers."""
    dim, longest = q.x.shape[1], float(c.norm[0]) if len(c.ids) else 0.0
    most = float(q.norm.max(initial=0)) * longest
    (qx, qt), (cx, ct) = (q.light(), c.light()) if most < 1 << 24 else ((q.x, q.turned), (c.x, c.turned))
    slack = (2e-6 * dim if most < 1 << 24 else 1e-9) * q.norm * longest + 1e-3
    least = floor.astype(np.float64).copy()
    who, ids, scores = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    finished = 0
    for at in range(0, len(c.ids), STEP):
        rows = np.flatnonzero(q.norm * c.norm[at] + slack >= least)
        if not len(rows):
            break
        to = min(at + STEP, len(c.ids))
        keep, done, part = np.ones((len(rows), to - at), bool), 0, 0
        if np.isfinite(least[rows]).any():
            for n, qr, cr in zip(q.cuts, q.rest, c.rest, strict=True):
                part = part + qt[rows, done:n] @ ct[at:to, done:n].T
                keep = part + np.outer(qr[rows], cr[at:to]) >= (least[rows] - slack[rows])[:, None]
                done = n
                if np.count_nonzero(keep) * 50 < keep.size:
                    break
        i, j = np.nonzero(keep)
        other = q.ids[rows[i]] != c.ids[at + j]
        i, j = rows[i[other]], at + j[other]
        finished += len(i)
        if most >= 1 << 53:
            found = np.fromiter((int(a @ b) for a, b in zip(q.x[i].astype(np.int64), c.x[j].astype(np.int64), strict=True)), np.int64, len(i))
        elif len(i) * 20 > keep.size:
            every = np.full(len(q.ids), -1)
            every[rows] = np.arange(len(rows))
            found = (qx[rows] @ cx[at:to].T)[every[i], j - at].astype(np.int64)
        else:
            found = np.einsum("ij,ij->i", q.x[i], c.x[j]).astype(np.int64)
        good = found >= least[i]
        if not good.any():
            continue
        who, ids, scores = np.concatenate([who, i[good]]), np.concatenate([ids, c.ids[j[good]]]), np.concatenate([scores, found[good]])
        who, ids, scores = first_k(who, ids, scores, k)
        full = np.flatnonzero(np.diff(np.concatenate([[0], np.cumsum(np.bincount(who, minlength=len(q.ids)))])) == k)
        last = np.searchsorted(who, full, "right") - 1
        least[full] = np.maximum(least[full], scores[last])
    return who, ids, scores, finished


def first_k(who: np.ndarray, ids: np.ndarray, scores: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k highest scores of each query, ties to the smaller id, by query and rank."""
    order = np.lexsort((ids, -scores, who))
    who, ids, scores = who[order], ids[order], scores[order]
    kept = np.arange(len(who)) - np.searchsorted(who, who) < k
    return who[kept], ids[kept], scores[kept]


def best(q: np.ndarray, q_id: np.ndarray, floor: np.ndarray, c: np.ndarray, c_id: np.ndarray, basis: np.ndarray, k: int):
    """For each query (rows of q) its k best candidates: (query, vec_id, score). c: longest first. floor: a
    score that k candidates are known to reach, or -inf. Also returned: how many products were finished."""
    who, ids, scores, finished = meet(Side(q, q_id, basis), floor, Side(c, c_id, basis), k)
    return list(zip(q_id[who].tolist(), ids.tolist(), scores.tolist(), strict=True)), finished


def known_floors(who: np.ndarray, scores: np.ndarray, n: int, k: int) -> np.ndarray:
    """The k-th best score of each of n queries, -inf where fewer are known. Rows lie by query and rank."""
    floor, number = np.full(n, -np.inf), np.bincount(who, minlength=n)
    full = np.flatnonzero(number >= k)
    floor[full] = scores[np.searchsorted(who, full) + k - 1]
    return floor


def groups_within(q: np.ndarray, floor: np.ndarray, tops: np.ndarray, ends: np.ndarray) -> int:
    """How many groups, from the longest candidates on, can hold one that reaches the floor of a query. tops:
    lengths that no candidate of a band passes; ends: the groups up to each band's end."""
    norm = np.sqrt((q * q).sum(axis=1))
    with np.errstate(divide="ignore", invalid="ignore"):
        least = np.where(norm > 0, (floor - 1e-6) / norm * (1 - 1e-9), np.where(floor <= 1e-6, -np.inf, np.inf))
    bands = np.flatnonzero(tops >= least.min(initial=np.inf))
    return int(ends[bands[-1]]) if len(bands) else 0


def narrow(x: np.ndarray) -> bytes:
    """Whole numbers in two bytes each where they fit, in eight as floats else, with a byte in front that tells."""
    return b"\2" + x.astype("<i2").tobytes() if np.abs(x).max(initial=0) < 1 << 15 else b"\10" + x.astype("<f8").tobytes()


def wide(b: bytes, dim: int) -> np.ndarray:
    return np.frombuffer(b, "<i2" if b[0] == 2 else "<f8", offset=1).astype(np.float64).reshape(-1, dim)


def _packed(rows: DataFrame, by: list[str]) -> DataFrame:
    """Rows of a block as one row of two binaries, longest first; blocks have a bounded number of rows."""

    def pack(block: pd.DataFrame) -> pd.DataFrame:
        block = block.sort_values(["norm", "vec_id"], ascending=[False, True])
        first = {c: [block[c].iat[0]] for c in by}
        return pd.DataFrame(first | {"ids": [block["vec_id"].to_numpy(np.int64).tobytes()], "x": [narrow(np.stack(block["v"].to_numpy()))]})

    return rows.groupBy(*by).applyInPandas(pack, ", ".join(f"{c} int" for c in by) + ", ids binary, x binary")


def top_k(rows: DataFrame, is_query: Column, k: int = K, scale: int = SCALE) -> DataFrame:
    """query_id, rank, vec_id, score."""
    spark = rows.sparkSession
    vectors = scaled(rows, scale)
    dims = vectors.groupBy(F.size("v").alias("d")).count().where("d > 0")
    first = dims.orderBy(F.desc("count"), F.desc("d")).first()
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    if first is None:
        return empty
    dim = first[0]
    vectors = cut(vectors.where(F.size("v") == dim), "vectors")
    basis = rotation(vectors, dim)
    n, n_queries = vectors.agg(F.count("*"), F.count_if(is_query)).first()
    blocks, bands = max(1, -(-n_queries // QUERY_BLOCK)), min(BANDS, -(-n // CANDIDATE_GROUP))
    # Lengths' quantiles bound the bands; a band is dealt by id into as many groups as its rows need.
    shares = [i / bands for i in range(1, bands)]
    bounds = sorted(set(vectors.approxQuantile("norm", shares, 0.001)), reverse=True) if shares else []
    band = F.lit(0)
    for b in bounds:
        band = band + (F.col("norm") < b).cast("int")
    sizes = dict(vectors.groupBy(band.alias("band")).count().collect())  # BANDS rows at most
    parts = [max(1, -(-sizes.get(i, 0) // CANDIDATE_GROUP)) for i in range(len(bounds) + 1)]
    offsets = [sum(parts[:i]) for i in range(len(parts))]
    of = lambda numbers: F.element_at(F.array(*map(F.lit, numbers)), F.col("band") + 1)
    group = of(offsets) + F.pmod(F.xxhash64("vec_id"), of(parts))
    candidates = vectors.withColumn("band", band).withColumn("group", group.cast("int"))
    packed = cut(_packed(candidates, ["group"]), "vector-groups")
    # The head is found by the executors, among the longest band only, and comes to the driver as two binaries.
    longest = cut((vectors.where(F.col("norm") >= bounds[0]) if bounds else vectors).orderBy(F.desc("norm"), "vec_id").limit(HEAD), "vector-head")
    head = _packed(longest.withColumn("block", F.lit(0)), ["block"]).first()
    head_ids, head_x = bytes(head["ids"]), bytes(head["x"])
    queries = vectors.where(is_query).withColumn("block", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(blocks)).cast("int"))
    side = lambda ids, x: Side(wide(x, dim), np.frombuffer(ids, np.int64), basis)

    def start(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        top = side(head_ids, head_x)
        for batch in batches:
            floors, reach = [], []
            for ids, x in zip(batch["ids"], batch["x"], strict=True):
                q = side(ids, x)
                who, _, scores, _ = meet(q, np.full(len(q.ids), -np.inf), top, k)
                floor = known_floors(who, scores, len(q.ids), k)
                floors.append(floor.tobytes())
                reach.append(groups_within(q.x, floor, tops, ends))
            yield batch.assign(floor=floors, groups=reach)

    tops, ends = np.array([np.inf, *bounds]), np.cumsum(parts)
    started = _packed(queries, ["block"]).mapInPandas(start, "block int, ids binary, x binary, floor binary, groups int")
    started = cut(started, "query-blocks")
    # Groups are dealt to sets, longest and shortest alike, and move once. A block goes to the sets that hold a group it has to
    # visit, in lots of blocks, so that what moves are queries times sets, not queries times groups.
    groups = sum(parts)
    sets, lots = min(groups, max(SETS, -(-groups // SET_GROUPS))), -(-blocks // LOT_BLOCKS)
    routed = started.where("groups > 0").withColumn("set", F.explode(F.sequence(F.lit(0), F.least("groups", F.lit(sets)) - 1)))
    routed = routed.withColumn("lot", F.pmod("block", F.lit(lots))).select("set", "lot", "ids", "x", "floor", "groups")
    held = packed.withColumn("set", F.pmod("group", F.lit(sets))).withColumn("lot", F.explode(F.sequence(F.lit(0), F.lit(lots - 1)))).select("set", "lot", "group", "ids", "x")

    def search(blocks: pd.DataFrame, own: pd.DataFrame) -> pd.DataFrame:
        found, own = [], own.sort_values("group")
        known = [side(r.ids, r.x) for r in own.itertuples()] if len(blocks) else []
        for r in blocks.itertuples():
            q, floor, got = side(r.ids, r.x), np.frombuffer(r.floor), [np.zeros(0, np.int64)] * 3
            for number, c in zip(own["group"], known, strict=False):
                if number < r.groups:
                    *more, _ = meet(q, floor, c, k)
                    got = first_k(*[np.concatenate(both) for both in zip(got, more, strict=True)], k)
                    floor = np.maximum(floor, known_floors(got[0], got[2], len(q.ids), k))
            found.append(pd.DataFrame({"query_id": q.ids[got[0]], "vec_id": got[1], "score": got[2]}))
        return pd.concat(found) if found else pd.DataFrame({c: np.zeros(0, np.int64) for c in ("query_id", "vec_id", "score")})

    deal = lambda df: df.repartition(max(2, sets * lots), "set", "lot").groupBy("set", "lot")
    found = cut(deal(routed).cogroup(deal(held)).applyInPandas(search, "query_id long, vec_id long, score long"), "top-parts")
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def op9_top_k(rows: DataFrame) -> DataFrame:
    return top_k(rows, F.col("vec_id") % 50 == 0)


SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id, list_inner_product(q.v, c.v)::BIGINT AS score
      FROM v q JOIN v c ON q.vec_id % 50 = 0 AND q.vec_id <> c.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM r WHERE rank <= 5
"""
