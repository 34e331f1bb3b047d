"""Quality rules whose thresholds come from the data: quantile sketches per language and source.

Five measures of a text (symbols per word character, word length both ways, repeated lines, repeated
passages) go into log-bucket quantile sketches: a value's bucket is the power of GAMMA it lies under, so a
sketch is a table of bucket counts with a relative error of one per cent, and merging two is adding their
counts. Sketches are built per language and source by a group-by with partial sums, and merged into
sketches of languages and of everything for groups too small to judge by. A measure's threshold is the
upper quartile plus FENCE spreads (for short words the lower quartile minus as much); the spread is the
distance of the quartiles, or a few times the sketch's own error where they lie closer. No threshold cuts
into the group's first TAIL of values: where quartiles are 0, as those of repeated text mostly are, the
tail alone says what is unusual. Documents are joined with their group's thresholds and filtered.

Defined results: a null text has no words and fails the base rule; null languages and sources form groups
of their own; repeated rows count as often as they occur; a threshold needs SMALLEST documents, else the
language's is used, else that of all; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from huecount.llm.common import cut, cut_texts, slices
from huecount.llm.minhash import WordHash, shingles

GAMMA = 1.02
FENCE = 3.0
#: Relative error of a bucket's middle, and the least spread as a part of the quartile.
ERROR = (GAMMA - 1) / (GAMMA + 1)
LEAST_SPREAD = 4 * ERROR
TAIL = 0.98
SMALLEST = 100
WINDOW = 5
# Fixed values of the base rule.
SYMBOLS = "#*$%&|<>"
BLANKS = " \t\n\x0b\x0c\r"
MIN_WORDS, MAX_REPEAT_PERCENT = 10, 20
#: measure: (numerator, denominator, upper fence, lower fence)
MEASURES = {
    "symbols": ("n_symbols", "word_chars", True, False),
    "word_length": ("word_chars", "n_words", True, True),
    "repeated_lines": ("n_dup_lines", "n_lines", True, False),
    "repeated_words": ("n_repeat_words", "n_words", True, False),
}
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")


def repeat_words(windows: np.ndarray, n_words: int) -> int:
    """Words that lie in a window which occurs twice or more."""
    if n_words <= WINDOW:
        return 0
    _, inverse, times = np.unique(windows, return_inverse=True, return_counts=True)
    starts = np.flatnonzero(times[inverse] > 1)
    if not len(starts):
        return 0
    edge = np.zeros(n_words + 1, np.int64)
    edge[starts] += 1
    np.add.at(edge, starts + WINDOW, -1)
    return int((np.cumsum(edge) > 0).sum())


def counts_of(text: str | None, known: WordHash) -> tuple[int, ...]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines of one whole text."""
    text = text or ""
    n = len(text.encode("utf-8", "surrogatepass").split())
    chars = len(text) - sum(map(text.count, BLANKS))
    symbols = sum(map(text.count, SYMBOLS))
    lines = [x for x in text.split("\n") if x.strip(BLANKS)]
    return n, chars, symbols, len(lines) - len(set(lines)), repeat_words(shingles(text, known, WINDOW), n), len(lines)


def measured(docs: DataFrame) -> DataFrame:
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known = WordHash()
        for batch in slices(batches):
            rows = pd.DataFrame([counts_of(t, known) for t in batch["text"]], columns=list(COUNTS), dtype="int64")
            yield pd.concat([batch[["doc_id", "lang", "source"]].reset_index(drop=True), rows], axis=1)

    light = docs.select(F.col("doc_id").cast("string").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("source").cast("string").alias("source"), "text")
    out = light.mapInPandas(run, "doc_id string, lang string, source string, " + ", ".join(f"{c} long" for c in COUNTS))
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    return out.withColumn("doc_id", F.col("doc_id").cast("long")).withColumn("base_failed", failed)


def sketches(rows: DataFrame) -> DataFrame:
    """lang, source, measure, bucket, n: the sketches of all groups. Bucket null: the value 0."""
    values = F.explode(F.array(*[F.struct(F.lit(m).alias("measure"), (F.col(a) / F.col(b)).alias("x")) for m, (a, b, *_) in MEASURES.items()]))
    bucket = F.when(F.col("v.x") > 0, F.ceil(F.round(F.log("v.x") / math.log(GAMMA), 9))).cast("int")
    flat = rows.where("not base_failed").select("lang", "source", values.alias("v")).select("lang", "source", "v.measure", bucket.alias("bucket"))
    return flat.groupBy("lang", "source", "measure", "bucket").agg(F.count("*").alias("n"))


def merged(sketch: DataFrame) -> DataFrame:
    """Sketches of (lang, source), of lang and of all, told apart by ``level`` 0, 1, 2."""
    level = lambda k, lang, source: sketch.select(F.lit(k).alias("level"), lang.alias("lang"), source.alias("source"), "measure", "bucket", "n")
    none = F.lit(None).cast("string")
    parts = level(0, F.col("lang"), F.col("source")).union(level(1, F.col("lang"), none)).union(level(2, none, none))
    return parts.groupBy("level", "lang", "source", "measure", "bucket").agg(F.sum("n").alias("n"))


def quantiles(sketch: DataFrame, wanted=(0.25, 0.75)) -> DataFrame:
    """level, lang, source, measure, total, q (array): bucket middles at the wanted shares."""
    group = ["level", "lang", "source", "measure"]
    upto = W.partitionBy(*group).orderBy(F.col("bucket").asc_nulls_first())
    seen = sketch.withColumn("seen", F.sum("n").over(upto)).withColumn("total", F.sum("n").over(W.partitionBy(*group)))
    middle = F.when(F.col("bucket").isNull(), F.lit(0.0)).otherwise(2 * F.pow(F.lit(GAMMA), F.col("bucket")) / (GAMMA + 1))
    at = [F.min(F.when(F.col("seen") >= F.ceil(q * F.col("total")), F.col("middle"))) for q in wanted]
    return seen.withColumn("middle", middle).groupBy(*group).agg(F.max("total").alias("total"), F.array(*at).alias("q"))


def thresholds(sketch: DataFrame) -> DataFrame:
    """One row per (lang, source): for each measure hi_ and lo_, from the smallest group that is large enough."""
    by_level = quantiles(merged(sketch), (1 - TAIL, 0.25, 0.75, TAIL))
    pivot = lambda k: by_level.where(F.col("level") == k).groupBy("lang", "source").agg(
        F.max("total").alias(f"n{k}"), *[F.max(F.when(F.col("measure") == m, F.col("q"))).alias(f"{m}_{k}") for m in MEASURES]
    )
    own, lang, every = pivot(0), pivot(1).drop("source").withColumnRenamed("lang", "lang_1"), pivot(2).drop("lang", "source")
    both = own.join(lang, F.col("lang").eqNullSafe(F.col("lang_1"))).join(every, F.lit(True), "left")
    out = [F.col("lang").alias("t_lang"), F.col("source").alias("t_source")]
    for m, (_, _, up, down) in MEASURES.items():
        q = F.when(F.col("n0") >= SMALLEST, F.col(f"{m}_0")).when(F.col("n1") >= SMALLEST, F.col(f"{m}_1")).otherwise(F.col(f"{m}_2"))
        spread = lambda at, q=q: FENCE * F.greatest(q[2] - q[1], LEAST_SPREAD * at)
        # A tail's own bucket lies inside: its values differ from the middle by ERROR at most.
        hi, lo = F.greatest(q[2] + spread(q[2]), (1 + 2 * ERROR) * q[3]), F.least(q[1] - spread(q[1]), (1 - 2 * ERROR) * q[0])
        out.append((hi if up else F.lit(None).cast("double")).alias(f"hi_{m}"))
        out.append((lo if down else F.lit(None).cast("double")).alias(f"lo_{m}"))
    return both.select(*out)


def judged(rows: DataFrame, limits: DataFrame) -> DataFrame:
    """rows with ``kept``: the base rule holds and no measure lies outside its group's fences."""
    bad = F.lit(False)
    for m, (a, b, up, down) in MEASURES.items():
        x = F.try_divide(F.col(a), F.col(b))
        if up:
            bad = bad | F.coalesce(x > F.col(f"hi_{m}"), F.lit(False))
        if down:
            bad = bad | F.coalesce(x < F.col(f"lo_{m}"), F.lit(False))
    on = F.col("lang").eqNullSafe(F.col("t_lang")) & F.col("source").eqNullSafe(F.col("t_source"))
    return rows.join(limits, on, "left").withColumn("kept", ~F.col("base_failed") & ~bad)


def quality(docs: DataFrame) -> DataFrame:
    rows = cut_texts(measured(docs), "quality-counts")
    sketch = cut(sketches(rows), "quality-sketches")
    limits = cut(thresholds(sketch), "quality-limits")
    return judged(rows, limits)


def op5_quality(docs: DataFrame) -> DataFrame:
    return quality(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_lines", "lang", "source")
