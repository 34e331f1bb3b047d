"""Best-fit packing by minimum bin slack.

Each document becomes its token ids and a closing id. Documents longer than a sequence are cut, the
remainder first; nothing else is. Pieces as long as a sequence are sequences already and never move. The
others, one a document at most, are dealt evenly into buckets of about BUCKET pieces, and each bucket is
packed by itself: for one sequence a subset-sum programme over a bitset finds the fullest combination of the
lengths still available, starting from the longest one. The combination is removed as often as the counts
allow, for as long as its lengths last it would be found again, so there are at most about as many rounds as
lengths. A bucket costs one sequence that is not full, of some thousands; in return ids move once, two
bytes each, no task holds more than a bucket, and no part of the work grows on the driver. The sequences are
written whole.

Defined results: a null or empty text is one piece with the closing id only; repeated rows are pieces
of their own; a text of any length is read whole, one that the fast tokenizer refuses by the exact one;
an empty table gives an empty result; other columns are dropped.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from huecount.llm.common import cut, fresh_dir, remove, slices, small_batches

SEQUENCE = 2048
CLOSING_ID = 0
VOCABULARY = "byte_bpe_50k"
#: Pieces of a bucket, in the mean. At two bytes an id a task holds 32 MB of ids at the very most, and twice that once widened.
BUCKET = 8192
PART = ("offset", "length", "doc_id", "piece", "start")


class Tokens:
    """Ids of the byte-level vocabulary as little-endian bytes. Texts are encoded in one go: a memory of words costs more than
    it saves where words are as many as in documents."""

    def __init__(self, vocabulary: str = VOCABULARY):
        import base64

        import public_tokenizers
        import tiktoken

        with open(public_tokenizers.path(f"{vocabulary}.tiktoken"), "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        end = {"<|endoftext|>": len(ranks)}
        coder = tiktoken.Encoding("bytes", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=end)
        self.short = lambda text: coder.encode_to_numpy(text, allowed_special="all").astype("<u4", copy=False).tobytes()
        self.vocabulary, self.exact = vocabulary, None

    def __call__(self, text: str) -> bytes:
        """Very long runs of white space are more than the fast tokenizer's pattern can hold; the exact one reads
        such texts."""
        try:
            return self.short(text)
        except ValueError:
            if self.exact is None:
                import public_tokenizers
                from tokenizers import Tokenizer

                self.exact = Tokenizer.from_file(public_tokenizers.path(f"{self.vocabulary}.json"))
            return np.asarray(self.exact.encode(text, add_special_tokens=False).ids, "<u4").tobytes()


def cut_points(n: int, sequence: int = SEQUENCE) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n tokens: the remainder, if any, comes first."""
    first = n % sequence or sequence
    return [(0, first)] + [(s, sequence) for s in range(first, n, sequence)]


def pieces(docs: DataFrame, sequence: int = SEQUENCE, vocabulary: str = VOCABULARY) -> DataFrame:
    """doc_id, piece, start, length, ids of every piece, and the place of the piece: the task that cut it and
    its number there. ids: little-endian, four bytes each for pieces as long as a sequence; two (four if the
    vocabulary needs it) in ``narrow`` for the others, which have to travel."""
    closing = CLOSING_ID.to_bytes(4, "little")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        tokens, task, nth = Tokens(vocabulary), TaskContext.get().partitionId(), 0
        for batch in slices(batches):
            out = []
            for doc, text in zip(batch["doc_id"], batch["text"], strict=True):
                doc = None if doc is None else int(doc)
                ids = tokens(text or "") + closing
                for k, (start, length) in enumerate(cut_points(len(ids) // 4, sequence)):
                    own, full = ids[4 * start : 4 * (start + length)], length == sequence
                    out.append((doc, k, start, length, own if full else None, None if full else narrowed(own), task, nth))
                    nth += 1
            made = pd.DataFrame(out, columns=["doc_id", "piece", "start", "length", "ids", "narrow", "task", "nth"])
            yield made.astype({"doc_id": "Int64"})

    # A null would turn a batch of ids into floats; as text they stay whole.
    light = docs.select(F.col("doc_id").cast("long").cast("string").alias("doc_id"), "text")
    return light.mapInPandas(run, "doc_id long, piece int, start long, length long, ids binary, narrow binary, task int, nth long")


def narrowed(ids: bytes) -> bytes:
    """The ids in two bytes each where they fit, with a byte in front that tells."""
    x = np.frombuffer(ids, "<u4")
    return b"\2" + x.astype("<u2").tobytes() if not len(x) or x.max() < 1 << 16 else b"\4" + ids


def widened(narrow: bytes) -> bytes:
    return np.frombuffer(narrow, "<u2", offset=1).astype("<u4").tobytes() if narrow[0] == 2 else narrow[1:]


def fullest(counts: list[int], sequence: int) -> list[int]:
    """Lengths of one sequence: the longest available one and, with it, the combination that leaves the
    least slack. counts[l]: pieces of length l."""
    longest = next(n for n in range(sequence, 0, -1) if counts[n])
    room = sequence - longest
    mask, reach, steps = (1 << (room + 1)) - 1, 1, []
    for n in range(min(longest, room), 0, -1):
        left = min(counts[n] - (n == longest), room // n)
        lot = 1
        while left > 0 and not reach >> room:
            take = min(lot, left)
            steps.append((reach, n, take))
            reach |= (reach << (n * take)) & mask
            left, lot = left - take, lot * 2
        if reach >> room:
            break
    at, chosen = reach.bit_length() - 1, [longest]
    for before, n, take in reversed(steps):
        if not before >> at & 1:
            at -= n * take
            chosen += [n] * take
    return chosen


def pack_histogram(histogram: dict[int, int], sequence: int = SEQUENCE) -> list[tuple[dict[int, int], int]]:
    """(lengths of a sequence with their numbers, how many such sequences) in the order found."""
    counts = [0] * (sequence + 1)
    for n, c in histogram.items():
        counts[n] += c
    found = []
    while any(counts):
        one: dict[int, int] = {}
        for n in fullest(counts, sequence):
            one[n] = one.get(n, 0) + 1
        times = min(counts[n] // c for n, c in one.items())
        for n, c in one.items():
            counts[n] -= c * times
        found.append((one, times))
    return found


def members(lengths: np.ndarray, sequence: int = SEQUENCE) -> Iterator[list[int]]:
    """For each sequence the numbers of its pieces, longest first. Equal lengths are taken in the order given."""
    order = np.argsort(lengths, kind="stable")
    sizes, first = np.unique(lengths[order], return_index=True)
    at = dict(zip(sizes.tolist(), first.tolist(), strict=True))
    histogram = dict(zip(sizes.tolist(), np.diff([*first, len(order)]).tolist(), strict=True))
    order = order.tolist()
    for one, times in pack_histogram(histogram, sequence):
        lots = sorted(one.items(), reverse=True)
        for _ in range(times):
            chosen = []
            for n, c in lots:
                chosen += order[at[n] : at[n] + c]
                at[n] += c
            yield chosen


def sequences(docs: DataFrame, sequence: int = SEQUENCE, bucket: int = BUCKET) -> DataFrame:
    """sequence_id, ids, parts (offset, length, doc_id, piece, start): the packed sequences, written whole, their
    pieces joined by offset."""
    spark, path = docs.sparkSession, fresh_dir(docs.sparkSession, "pieces")
    made = pieces(docs, sequence).withColumn("full", F.col("length") == sequence)
    with small_batches(spark):
        made.write.option("compression", "zstd").partitionBy("full").parquet(path)
    written = spark.read.schema(made.schema).parquet(path)
    loose = written.where("not full").drop("full")
    buckets = max(1, -(-loose.count() // bucket))

    def pack(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["task", "nth"], ignore_index=True)
        lengths, narrow = rows["length"].to_numpy(np.int64), rows["narrow"].tolist()
        docs = [None if d is None else int(d) for d in rows["doc_id"]]
        light = list(zip(lengths.tolist(), docs, rows["piece"].tolist(), rows["start"].tolist(), strict=True))
        base, out = int(rows["bucket"].iat[0]) << 32, []
        for k, chosen in enumerate(members(lengths, sequence)):
            offset, parts = 0, []
            for i in chosen:
                parts.append((offset, *light[i]))
                offset += light[i][0]
            out.append(((base + k) * 2, b"".join(widened(narrow[i]) for i in chosen), [dict(zip(PART, p, strict=True)) for p in parts]))
        return pd.DataFrame(out, columns=["sequence_id", "ids", "parts"])

    shape = "sequence_id long, ids binary, parts array<struct<offset:long,length:long,doc_id:long,piece:int,start:long>>"
    loose = loose.withColumn("doc_id", F.col("doc_id").cast("string"))  # a null would turn a bucket's ids into floats
    dealt = loose.withColumn("bucket", F.pmod(F.xxhash64("task", "nth"), F.lit(buckets)))
    packed = dealt.drop("ids").groupBy("bucket").applyInPandas(pack, shape)
    packed = cut(packed, "sequences", compression="zstd")
    remove(spark, f"{path}/full=false")  # these lie in sequences now
    written = spark.read.schema(made.schema).parquet(path)
    whole = F.array(F.struct(F.lit(0).cast("long").alias("offset"), "length", "doc_id", "piece", "start"))
    number = (F.shiftleft(F.col("task").cast("long"), 40) + F.col("nth")) * 2 + 1
    full = written.where("full").select(number.alias("sequence_id"), "ids", whole.alias("parts"))
    return packed.union(full)


def placed(packed: DataFrame) -> DataFrame:
    """doc_id, piece, start, length, sequence_id, offset, ids of every piece, the pieces of a sequence in order and
    their ids taken from the sequence."""
    rows = packed.select("sequence_id", "ids", F.explode("parts").alias("p"))
    own = F.substring("ids", (4 * F.col("p.offset") + 1).cast("int"), (4 * F.col("p.length")).cast("int"))
    return rows.select("p.doc_id", "p.piece", "p.start", "p.length", "sequence_id", "p.offset", own.alias("ids"))


def op4_packing(docs: DataFrame) -> DataFrame:
    return placed(sequences(docs)).select("doc_id", "piece", "start", "length", F.crc32("ids").alias("ids_crc32"), "sequence_id", "offset")
