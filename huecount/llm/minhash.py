"""Near-duplicate classes by dart-throwing weighted MinHash.

A text is a weighted set: its five-word shingles, weighted by how often they occur. Every element owns a
region that is as wide as its weight; hashed darts hit the plane of (width, time) at rate one, always at
the same points for the same element. Each dart carries a coordinate. The earliest dart of every
coordinate, over all elements of the set, is the signature; two sets agree in a coordinate with the
probability of their weighted Jaccard similarity. Darts are thrown in time order, so only the first few
regions of a long text are touched more than once: about K (ln K + 2) darts a text, however long.

Texts that are equal are one node. Nodes that agree in all rows of a band share a bucket. One rule makes a link,
whatever the bucket: signatures that agree in WORTH_CHECKING of their coordinates (six standard errors below the
threshold) and, exactly, a weighted similarity of 0.8 or more. A bucket's hub is the member that shares most
buckets with others; each node is compared with two of its buckets' hubs, and links join nodes into classes.
Buckets whose members are then still in several classes compare every pair of members from different classes:
small ones by a join, large ones a block of members against a block, which emits links only. Within a class no
further link is needed.

Weights are whole numbers, so the weighted similarity is the plain one of cells: the k-th occurrence of an element
is a cell of its own.

Defined results: a null text, or one without words, is a class of its own, whatever its id; a text of fewer than
five words is one shingle; repeated rows fall into one class, rows that repeat an id with different texts into those
of their texts; an empty table gives an empty result; other columns are ignored. Class id: the smallest doc_id of
the class, null if none has one.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from huecount.llm.common import cut, cut_texts, made, settle, slices

SHINGLE = 5
BANDS, ROWS = 32, 5
THRESHOLD = 0.8
#: Signatures of 160 rows estimate 0.8 with a standard error of 0.032: below this it is six errors off.
WORTH_CHECKING = 0.6
#: Buckets of so many members are compared by a join, larger ones in blocks. The rule for a link is the same.
PAIRWISE_UP_TO = 24
#: Members and cells of a block, about.
BLOCK, BLOCK_CELLS = 1024, 1 << 20
MEMORY_WORDS = 250_000
CHUNK_BITS = 32768
#: A bitmap of ids has 16 MB at most. From some 8 million ids on it fills up and sorts out less and less; results
#: are exact all the same, for a join follows, but that join then moves more rows.
MAX_BITS = 1 << 27
#: A text or class with more than this share of all rows is hot; there are HOT of them at most.
HOT = 1024
_MIX1, _MIX2, _GOLDEN = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB), np.uint64(0x9E3779B97F4A7C15)


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser with good avalanche."""
    x = x + _GOLDEN
    x = (x ^ (x >> np.uint64(30))) * _MIX1
    x = (x ^ (x >> np.uint64(27))) * _MIX2
    return x ^ (x >> np.uint64(31))


class WordHash(dict):
    """64-bit hashes of words, remembered up to a bound."""

    def __missing__(self, word: bytes) -> int:
        import xxhash

        h = xxhash.xxh3_64_intdigest(word)
        if len(self) < MEMORY_WORDS:
            self[word] = h
        return h


def shingles(text: str | None, known: WordHash, width: int = SHINGLE) -> np.ndarray:
    """Hashes of all windows of ``width`` words (repeats kept); a shorter text is one window."""
    words = text.encode("utf-8", "surrogatepass").split() if text else ()
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(known.__getitem__, words), np.uint64, n)
    width = min(width, n)
    total = np.full(n - width + 1, width, np.uint64)
    for k in range(width):
        total = mixed(total ^ h[k : n - width + 1 + k])
    return total


def weighted(sh: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct elements and weights, the numbers of their occurrences."""
    e, w = np.unique(sh, return_counts=True)
    return e, w.astype(np.float64)


def cells(elements: np.ndarray, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The cells of width one that the elements' regions are cut into, and how much of each lies in its region."""
    whole = np.ceil(weights).astype(np.int64)
    nth = np.arange(whole.sum()) - np.repeat(np.cumsum(whole) - whole, whole)
    return mixed(np.repeat(elements, whole) ^ mixed(nth.astype(np.uint64))), np.minimum(np.repeat(weights, whole) - nth, 1.0)


def _uniform(x: np.ndarray) -> np.ndarray:
    return ((x >> np.uint64(11)).astype(np.float64) + 0.5) * (1.0 / (1 << 53))


def dart_signatures(sets: list[tuple[np.ndarray, np.ndarray]], k: int = BANDS * ROWS) -> np.ndarray:
    """(sets x k) uint64: for every coordinate the earliest dart. Empty sets give zeros.

    In each cell darts arrive over time as a Poisson process of rate one, with a uniform place in the cell. A
    dart past the weight is a miss."""
    out = np.zeros((len(sets), k), np.uint64)
    owner, cell, room = [], [], []
    for i, (elements, weights) in enumerate(sets):
        if len(elements) == 0 or not weights.any():
            continue
        own, within = cells(elements, weights)
        owner.append(np.full(len(own), i))
        cell.append(own)
        room.append(within)
    if not owner:
        return out
    owner, cell, room = np.concatenate(owner), np.concatenate(cell), np.concatenate(room)
    mass = np.bincount(owner, weights=room, minlength=len(sets))
    horizon = np.divide(k * (np.log(k) + 2.0), mass, out=np.zeros(len(sets)), where=mass > 0)
    best = np.full(len(sets) * k, np.inf)
    name = np.zeros(len(sets) * k, np.uint64)
    clock, turn = np.zeros(len(cell)), cell.copy()
    while True:
        live = np.arange(len(cell))
        while len(live):  # the next dart of every cell that has not passed its set's horizon
            turn_l = mixed(turn[live])
            clock_l = clock[live] - np.log(_uniform(mixed(turn_l ^ np.uint64(1))))
            early = clock_l <= horizon[owner[live]]
            live = live[early]
            turn[live], clock[live] = turn_l[early], clock_l[early]
            if not len(live):
                break
            dart = mixed(turn[live] ^ np.uint64(2))
            hit = _uniform(mixed(dart ^ np.uint64(3))) <= room[live]
            at = owner[live[hit]] * k + (dart[hit] % np.uint64(k)).astype(np.int64)
            when, dart = clock[live[hit]], dart[hit]
            order = np.argsort(-when, kind="stable")  # the earliest is written last
            at, when, dart = at[order], when[order], dart[order]
            better = when < best[at]
            best[at[better]], name[at[better]] = when[better], dart[better]
        short = np.isinf(best).reshape(len(sets), k).any(axis=1) & (mass > 0)
        if not short.any():
            break
        horizon = np.where(short, horizon * 2, horizon)
        keep = short[owner]
        owner, cell, room, clock, turn = owner[keep], cell[keep], room[keep], clock[keep], turn[keep]
    out[:] = np.where(np.isinf(best), 0, name).astype(np.uint64).reshape(len(sets), k)
    return out


def band_keys(signatures: np.ndarray, bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    """(sets x bands) int64: one hash of each band's rows, different between bands."""
    parts = signatures.reshape(len(signatures), bands, rows)
    key = mixed(np.arange(bands, dtype=np.uint64))[None, :] + np.zeros((len(signatures), 1), np.uint64)
    for r in range(rows):
        key = mixed(key ^ parts[:, :, r])
    return key.view(np.int64)


def digest(text: Column | str = "text") -> Column:
    """16 bytes that stand for a text."""
    whole = F.sha2(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")).cast("binary"), 256)
    return F.unhex(F.substring(whole, 1, 32))


def signed(docs: DataFrame) -> DataFrame:
    """row (a number of its own), doc_id, digest of the text, n (cells), keys (one per band), sig (16 bits a
    coordinate). To be written before it is read twice: rows are numbered as tasks come by them."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        known, next_row = WordHash(), TaskContext.get().partitionId() << 40
        for batch in slices(batches):
            sets = [weighted(shingles(t, known)) for t in batch["text"]]
            sig = dart_signatures(sets)
            yield pd.DataFrame(
                {
                    "row": np.arange(next_row, next_row + len(batch)),
                    "doc_id": batch["doc_id"],
                    "digest": batch["digest"],
                    "n": [int(w.sum()) for _, w in sets],
                    "keys": list(band_keys(sig)),
                    "sig": [x.tobytes() for x in (sig >> np.uint64(48)).astype("<u2")],
                }
            )
            next_row += len(batch)

    light = docs.select(F.col("doc_id").cast("long").cast("string").alias("doc_id"), "text", digest().alias("digest"))
    made = light.mapInPandas(run, "row long, doc_id string, digest binary, n long, keys array<long>, sig binary")
    return made.withColumn("doc_id", F.col("doc_id").cast("long"))


@F.pandas_udf(T.DoubleType())
def agreement(a: pd.Series, b: pd.Series) -> pd.Series:
    """Share of coordinates in which two signatures agree."""
    if not len(a):
        return pd.Series([], dtype="float64")
    x, y = (np.frombuffer(b"".join(s), "<u2").reshape(len(s), -1) for s in (a, b))
    return pd.Series((x == y).mean(axis=1))


def may_be_among(df: DataFrame, column: str, ids: DataFrame, flag: str = "may_be") -> DataFrame:
    """df with a flag that is true where the column is among ids (one column), and false for most other rows,
    without a shuffle of df: a bitmap of hashed ids, 16 bits an id up to MAX_BITS, goes to every task."""
    name, bits, n = ids.columns[0], 1 << 15, ids.count()
    while bits < MAX_BITS and bits < 16 * n:
        bits *= 2
    slot = lambda c: F.pmod(F.xxhash64(c), F.lit(bits))
    chunk = F.floor(slot(F.col(name)) / CHUNK_BITS).cast("int")
    bitmap = ids.groupBy(chunk.alias("bit_chunk")).agg(F.bitmap_construct_agg(slot(F.col(name)) % CHUNK_BITS).alias("bit_map"))
    bitmap = cut(bitmap, "dup-bitmap")
    place = (slot(F.col(column)) % CHUNK_BITS).cast("int")
    byte = F.conv(F.hex(F.substring("bit_map", F.floor(place / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    on = F.floor(slot(F.col(column)) / CHUNK_BITS).cast("int") == F.col("bit_chunk")
    found = df.join(F.broadcast(bitmap), on, "left")  # MAX_BITS / 8 bytes at most
    hit = F.coalesce(F.call_function("shiftright", byte, place % 8).bitwiseAND(1) == 1, F.lit(False))
    return found.select(*[F.col(f"`{c}`") for c in df.columns], hit.alias(flag))


def likely_among(df: DataFrame, column: str, ids: DataFrame) -> DataFrame:
    """Rows of df whose column may be among ids, most others gone. An exact join comes after."""
    return may_be_among(df, column, ids).where("may_be").drop("may_be")


def shingle_sets(texts: DataFrame) -> DataFrame:
    """node, set: the cells of each text as 64-bit numbers."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known = WordHash()
        for batch in slices(batches):
            yield pd.DataFrame({"node": batch["node"], "set": [np.sort(cells(*weighted(shingles(t, known)))[0]).view(np.int64) for t in batch["text"]]})

    return texts.mapInPandas(run, "node long, set array<long>")


def _sets_of(docs: DataFrame, nodes: DataFrame, wanted: DataFrame) -> DataFrame:
    """Cells of the wanted nodes (one column). Of equal texts one is read; partial sums see to that before any of
    them moves."""
    of = cut(nodes.select("node", "digest").join(wanted, "node", "left_semi"), "dup-wanted")
    texts = likely_among(docs.select(digest().alias("digest"), "text"), "digest", of.select("digest"))
    once = texts.groupBy("digest").agg(F.first("text").alias("text"))
    return cut_texts(shingle_sets(once.join(of, "digest").select("node", "text")), "dup-shingles")


def verified(pairs: DataFrame, nodes: DataFrame, docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """Of pairs (a, b) the links. Signatures sort out most of the others before any text is read again."""
    sig_a, sig_b = (nodes.select(F.col("node").alias(x), F.col("sig").alias(f"sig_{x}")) for x in "ab")
    likely = pairs.join(sig_a, "a").join(sig_b, "b").where(agreement("sig_a", "sig_b") >= WORTH_CHECKING).select("a", "b")
    likely = cut(likely, "dup-likely")
    wanted = likely.select(F.col("a").alias("node")).union(likely.select("b")).distinct()
    sets = _sets_of(docs, nodes, wanted)
    a, b = (sets.select(F.col("node").alias(x), F.col("set").alias(f"set_{x}")) for x in "ab")
    both = F.size(F.array_intersect("set_a", "set_b"))
    either = F.size("set_a") + F.size("set_b") - both
    compared = likely.join(a, "a").join(b, "b").select("a", "b", both.alias("both"), either.alias("either"))
    return compared.where(F.col("both") >= F.col("either") * F.lit(threshold) - F.lit(1e-9)).select("a", "b")


def _stars(edges: DataFrame) -> bool:
    """Whether every node (u, v) hangs on one smaller node that hangs on none."""
    ends = edges.select(F.col("u").alias("node"), F.lit(1).alias("down"), F.lit(0).alias("up")).union(edges.select("v", F.lit(0), F.lit(1)))
    odd = (F.col("down") > 1) | ((F.col("down") > 0) & (F.col("up") > 0))
    return ends.groupBy("node").agg(F.sum("down").alias("down"), F.max("up").alias("up")).agg(F.count_if(odd)).first()[0] == 0


def components(edges: DataFrame) -> DataFrame:
    """node, label of every node that has an edge (a, b); label: the smallest node it is connected with.
    Alternates two star contractions until nothing changes; every step is a group-by and a join."""
    near = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "cc")
    while not _stars(near):
        ways = near.union(near.select("v", "u"))
        low = ways.groupBy("u").agg(F.least("u", F.min("v")).alias("m"))
        large = ways.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u")
        kept = small.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        near = cut(kept.union(low.select("u", F.col("m").alias("v"))).distinct(), "cc")
    return near.select(F.col("u").alias("node"), F.col("v").alias("label")).union(near.select("v", "v").distinct())


def _star_pairs(members: DataFrame) -> DataFrame:
    """Two hubs for each node: the one that most of its buckets name, and the busiest one. A bucket's hub is
    the member that shares most buckets with others, near the middle of its class."""
    busy = members.groupBy("node").agg(F.sum("n").alias("busy"))
    marked = members.join(busy, "node")
    hubs = marked.groupBy("key").agg(F.max(F.struct("busy", (-F.col("node")).alias("m"))).alias("hub"))
    named = members.join(hubs, "key").groupBy("node", "hub").agg(F.count("*").alias("times"))
    named = named.where(F.col("node") != -F.col("hub.m"))
    chosen = named.groupBy("node").agg(F.max(F.struct("times", "hub")).getField("hub").getField("m").alias("x"), F.max(F.struct("hub", "times")).getField("hub").getField("m").alias("y"))
    both = chosen.select("node", F.explode(F.array(-F.col("x"), -F.col("y"))).alias("other"))
    return both.select(F.least("node", "other").alias("a"), F.greatest("node", "other").alias("b")).distinct()


def similarities(left: list[np.ndarray], right: list[np.ndarray], width: int = 4096) -> np.ndarray:
    """Jaccard similarities of all sets on the left with all on the right, by products of 0/1 matrices of
    ``width`` elements at a time. Elements of one set only cannot meet and are left out."""
    sets = [*left, *right]
    sizes = np.array([len(s) for s in sets], np.float64)
    element, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), sizes.astype(np.int64))
    _, column, times = np.unique(element, return_inverse=True, return_counts=True)
    column = np.where(times > 1, np.cumsum(times > 1) - 1, -1)[column]
    owner, column = owner[column >= 0], column[column >= 0]
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    both = np.zeros((len(left), len(right)), np.float32)
    for at in range(0, int(column[-1]) + 1 if len(column) else 0, width):
        a, b = np.searchsorted(column, [at, at + width])
        part = np.zeros((len(sets), width), np.float32)
        part[owner[a:b], column[a:b] - at] = 1
        both += part[: len(left)] @ part[len(left) :].T
    either = sizes[: len(left), None] + sizes[None, len(left) :] - both
    return both / np.maximum(either, 1)


def agreements(left: list[bytes], right: list[bytes]) -> np.ndarray:
    """Shares of coordinates in which the signatures on the left agree with those on the right."""
    x, y = (np.frombuffer(b"".join(s), "<u2").reshape(len(s), -1) for s in (left, right))
    same = np.zeros((len(x), len(y)), np.int32)
    for k in range(x.shape[1]):
        same += x[:, k, None] == y[None, :, k]
    return same / x.shape[1]


def _cross_pairs(members: DataFrame, labels: DataFrame, nodes: DataFrame, docs: DataFrame, threshold: float) -> tuple[DataFrame, DataFrame]:
    """Members of one bucket that are still in different classes: pairs to be checked from small buckets,
    checked links from large ones."""
    labels = labels.select("node", F.col("label"))
    placed = members.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    split = placed.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo <> hi").select("key")
    placed = cut(placed.join(split, "key", "left_semi"), "dup-split")
    few = placed.where(F.col("n") <= PAIRWISE_UP_TO)
    x, y = few.select("key", F.col("node").alias("a"), F.col("label").alias("la")), few.select("key", F.col("node").alias("b"), F.col("label").alias("lb"))
    pairs = x.join(y, "key").where("a < b and la <> lb").select("a", "b")
    # Members of a large bucket's largest class have no need to meet each other: the others, in blocks,
    # meet all members, in blocks. Who meets whom is settled before any set moves.
    many = placed.where(F.col("n") > PAIRWISE_UP_TO).join(nodes.select("node", "cells"), "node")
    many = cut(many, "dup-large")
    per_class = many.groupBy("key", "label").agg(F.count("*").alias("c"), F.sum("cells").alias("cells"))
    largest = per_class.groupBy("key").agg(F.max(F.struct("c", "label", "cells")).alias("top"), F.sum("c").alias("c"), F.sum("cells").alias("cells"))
    blocks = lambda c, x: F.greatest(F.ceil(c / BLOCK), F.ceil(x / BLOCK_CELLS), F.lit(1)).cast("int")
    wide, tall = blocks(F.col("c"), F.col("cells")), blocks(F.col("c") - F.col("top.c"), F.col("cells") - F.col("top.cells"))
    largest = cut(largest.select("key", F.struct(F.col("top.label").alias("label"), wide.alias("wide"), tall.alias("tall")).alias("top"), "c"), "dup-largest")
    least = many.count() / HOT
    hot, cold = largest.where(F.col("c") > least), largest.where(F.col("c") <= least)
    many = many.join(F.broadcast(hot.select(F.col("key").alias("h_key"), F.col("top").alias("h_top"))), F.col("key") == F.col("h_key"), "left")  # HOT rows at most
    cold = many.where("h_key is null").join(cold.select("key", F.col("top").alias("c_top")), "key")
    met = lambda rows, top: rows.select("key", "node", F.col("label").alias("own_label"), F.col(f"{top}.label").alias("top_label"), f"{top}.wide", f"{top}.tall")
    many = cut(met(many.where("h_key is not null"), "h_top").union(met(cold, "c_top")), "dup-meeting")
    own = lambda parts: F.pmod(F.xxhash64("node"), F.col(parts)).cast("int")
    every = lambda parts: F.explode(F.sequence(F.lit(0), F.col(parts) - 1))
    left = many.where("own_label <> top_label").withColumn("j", every("wide")).withColumn("i", own("tall")).withColumn("side", F.lit(0))
    right = many.withColumn("i", every("tall")).withColumn("j", own("wide")).withColumn("side", F.lit(1))
    shape = ["key", "node", "own_label", "side", "i", "j"]
    sets = _sets_of(docs, nodes, many.select("node").distinct()).join(nodes.select("node", "sig"), "node")
    many = left.select(*shape).union(right.select(*shape)).withColumnRenamed("own_label", "label").join(sets, "node")

    def compare(rows: pd.DataFrame) -> pd.DataFrame:
        left, right = rows[rows["side"] == 0], rows[rows["side"] == 1]
        out = []
        if len(left) and len(right):
            alike = similarities(left["set"].tolist(), right["set"].tolist()) >= threshold - 1e-9
            alike &= agreements(left["sig"].tolist(), right["sig"].tolist()) >= WORTH_CHECKING
            nl, nr, ll, lr = left["node"].to_numpy(), right["node"].to_numpy(), left["label"].to_numpy(), right["label"].to_numpy()
            for k in np.flatnonzero(alike.any(axis=1)):
                hit = np.flatnonzero(alike[k] & (lr != ll[k]))
                _, first = np.unique(lr[hit], return_index=True)  # one link to a class is enough
                out += [(min(nl[k], b), max(nl[k], b)) for b in nr[hit[first]]]
        return pd.DataFrame(out, columns=["a", "b"], dtype="int64")

    links = many.groupBy("key", "i", "j").applyInPandas(compare, "a long, b long")
    return pairs.distinct(), links.distinct()


def _classes(nodes: DataFrame, docs: DataFrame, threshold: float) -> DataFrame:
    """node, label of all nodes that have a link."""
    spread = nodes.select("node", F.explode("keys").alias("key"))
    shared = spread.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    members = cut(spread.join(shared, "key"), "dup-members")
    first = cut(_star_pairs(members), "dup-pairs")
    with_company = cut(members.select("node").distinct(), "dup-company")
    nodes = cut(likely_among(nodes.select("node", "digest", "cells", "sig"), "node", with_company), "dup-sigs")  # a few more than have company
    links = cut(verified(first, nodes, docs, threshold), "dup-links")
    labels = cut(components(links), "dup-labels")
    pairs, more = _cross_pairs(members, labels, nodes, docs, threshold)
    second = cut(pairs.join(first, ["a", "b"], "left_anti"), "dup-pairs")
    more = cut(verified(second, nodes, docs, threshold).union(more), "dup-links")
    if more.isEmpty():
        return labels
    links = labels.select(F.col("node").alias("a"), F.col("label").alias("b")).where("a <> b").union(more)
    return cut(components(links), "dup-labels")


def grouped(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """row, doc_id, digest, copy_of (smallest doc_id with an equal text), label (a number for each class), first (smallest
    doc_id of the class), alone (no other row is in the class) of every row. A row without words is alone."""
    since = made()
    rows = cut_texts(signed(docs), "dup-signed")
    full, least = rows.where("n > 0"), rows.count() / HOT
    copied = full.groupBy("digest").agg(F.count("*").alias("copies"), F.min("row").alias("node"), F.min("doc_id").alias("first")).where("copies > 1")
    copied = cut(copied.withColumn("hot", F.col("copies") > least), "dup-copied")
    # Hot texts, HOT at most, go to every task, and their rows meet nothing in the join of the others.
    hot = copied.where("hot").select(F.col("digest").alias("h_digest"), F.col("node").alias("h_node"), F.col("first").alias("h_first"))
    cold = copied.where("not hot").select(F.col("digest").alias("c_digest"), F.col("node").alias("c_node"), F.col("first").alias("c_first"))
    ids = full.select("row", "doc_id", "digest").join(F.broadcast(hot), F.col("digest") == F.col("h_digest"), "left")
    nowhere = F.col("row").cast("string").cast("binary")
    ids = ids.join(cold, F.when(F.col("h_node").isNull(), F.col("digest")).otherwise(nowhere) == F.col("c_digest"), "left")
    node, first = F.coalesce("h_node", "c_node", "row"), F.when(F.col("h_node").isNotNull(), F.col("h_first")).when(F.col("c_node").isNotNull(), F.col("c_first")).otherwise(F.col("doc_id"))
    copy = F.col("h_node").isNotNull() | F.col("c_node").isNotNull()
    ids = cut(ids.select("row", "doc_id", "digest", node.alias("node"), first.alias("first"), copy.alias("copy"), F.col("h_node").isNotNull().alias("hot")), "dup-ids")
    nodes = full.join(ids.where("row <> node").select("row"), "row", "left_anti")
    nodes = cut(nodes.select(F.col("row").alias("node"), "digest", F.col("n").alias("cells"), "keys", "sig"), "dup-nodes")
    labels = _classes(nodes, docs, threshold)
    per_node = labels.join(ids.where("row = node").select("node", "first", "hot"), "node")
    of_class = per_node.groupBy("label").agg(F.min("first").alias("class_first"))
    per_node = cut(per_node.join(of_class, "label").select(F.col("node").alias("l_node"), "label", "class_first", "hot"), "dup-classes")
    hot = per_node.where("hot").select(F.col("l_node").alias("h_node"), F.col("label").alias("h_label"), F.col("class_first").alias("h_first"))
    cold = per_node.where("not hot").drop("hot")
    ids = ids.join(F.broadcast(hot), F.col("node") == F.col("h_node"), "left")
    ids = ids.join(cold, F.when(F.col("hot"), -1 - F.col("row")).otherwise(F.col("node")) == F.col("l_node"), "left")
    linked = F.col("h_node").isNotNull() | F.col("l_node").isNotNull()
    class_first = F.when(F.col("h_node").isNotNull(), F.col("h_first")).when(F.col("l_node").isNotNull(), F.col("class_first")).otherwise(F.col("first"))
    of_text = ids.select("row", "doc_id", "digest", F.col("first").alias("copy_of"), F.coalesce("h_label", "label", "node").alias("label"), class_first.alias("first"), (~linked & ~F.col("copy")).alias("alone"))
    empty = rows.where("n = 0").select("row", "doc_id", "digest", F.col("doc_id").alias("copy_of"), F.col("row").alias("label"), F.col("doc_id").alias("first"), F.lit(True).alias("alone"))
    return settle(of_text.union(empty), "dup-groups", since)


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, node (the smallest doc_id with an equal text), class_id, of every row of docs(doc_id, text)."""
    return grouped(docs, threshold).select("doc_id", F.col("copy_of").alias("node"), F.col("first").alias("class_id"))


def op6_near_duplicates(docs: DataFrame) -> DataFrame:
    return near_duplicates(docs)


def deduplicated(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """docs with one row of each class: that of the smallest doc_id (a null one comes last), of the smallest digest
    if that id stands for several texts. Rows without words stay."""
    since = made()
    rows = cut(grouped(docs, threshold).where("not alone"), "dup-classes")
    order = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "digest")
    stays = rows.groupBy("label").agg(F.min(order).alias("o")).select(F.col("o.doc_id").alias("doc_id"), F.col("o.digest").alias("digest"))
    every = rows.groupBy("doc_id", "digest").agg(F.count("*").alias("copies"))
    name = F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("~")).cast("binary"), "digest")
    stays = stays.select(name.alias("stays_name"))
    fate = every.withColumn("name", name).join(stays, F.col("name") == F.col("stays_name"), "left").where("stays_name is null or copies > 1")
    fate = settle(fate, "dup-fate", since)
    fate = fate.select(F.col("name").alias("fate_name"), F.col("stays_name").isNotNull().alias("fate_stays"))
    own = F.concat(F.coalesce(F.col("doc_id").cast("long").cast("string"), F.lit("~")).cast("binary"), digest())
    marked = may_be_among(docs.withColumn("fate_own", own), "fate_own", fate.select("fate_name"), "fate_may")
    free = marked.where("not fate_may").drop("fate_may", "fate_own")
    met = marked.where("fate_may").join(fate, F.col("fate_own") == F.col("fate_name"), "left")
    rest = met.where("fate_name is null").drop("fate_may", "fate_own", "fate_name", "fate_stays")
    # Several equal rows stay once; which of them does not matter to the text, and partial sums keep them apart.
    often = met.where("fate_stays").dropDuplicates(["fate_own"]).drop("fate_may", "fate_own", "fate_name", "fate_stays")
    return free.unionByName(rest).unionByName(often)
