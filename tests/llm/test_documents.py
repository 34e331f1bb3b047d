"""Operators on documents: small fixtures, edge cases, brute force."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from huecount.llm import langid, minhash, mixing, packing, quality, secrets, sharding

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, label int, n long, size string"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def documents():
    rng = random.Random(5)
    words = [a + b for a in "bcdfglmnprst" for b in ("ab", "en", "ion", "ou", "ul")]
    rows = []
    for i in range(60):
        text = " ".join(rng.choice(words) for _ in range(rng.randint(12, 160)))
        rows.append((i, text, "en" if i % 3 else "de", f"s{i % 4}" if i % 5 else "s0", len(text), i, i, "x"))
    base = rows[3][1].split()
    near = base[:]
    near[len(near) // 2] = "changed"
    rows += [(100, rows[0][1], "en", "s1", 1, 0, 0, None), (101, " ".join(near), None, "s2", 2, 0, 0, None)]
    rows += [(102, None, "en", None, None, None, None, None), (103, "", "fr", "s1", 0, 0, 0, ""), (104, " \n\t", None, None, 3, 0, 0, "y")]
    rows += [(105, "word " * 4000, "en", "s3", 0, 0, 0, None), (106, "é ü 日本語 <|endoftext|> a  b\n\n c ", "fr", "s3", 0, 0, 0, None), (107, "short one", "en", "s1", 0, 0, 0, None)]
    rows += [rows[7], rows[7], (None, "no id at all but some words are here", "en", "s1", 0, 0, 0, None)]
    return rows


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(documents(), SCHEMA).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_empty_tables(empty):
    for f in (langid.op1_language_id, sharding.op2_sharding, mixing.op3_mixing, packing.op4_packing, quality.op5_quality, minhash.op6_near_duplicates, secrets.op10_secret_scan):
        assert f(empty).count() == 0
    for f in (langid.identified, minhash.deduplicated, secrets.redacted, mixing.mix):
        assert f(empty).count() == 0


def test_shards(docs):
    rows = sharding.op2_sharding(docs).collect()
    given = Counter((r[0], len((r[1] or "").encode()) + 1, zlib.crc32((r[1] or "").encode())) for r in documents())
    assert Counter((r["doc_id"], r["size"], r["text_crc32"]) for r in rows) == given
    slots = defaultdict(list)
    for r in rows:
        slots[r["shard"]].append(r["slot"])
    assert all(sorted(s) == list(range(len(s))) for s in slots.values()) and set(slots) <= set(range(16))


def test_flow_moves_the_fewest_bytes():
    rng = random.Random(1)
    for _ in range(20):
        old = {i: rng.randint(0, 500) for i in range(5)}
        want = sharding.even_capacities(sum(old.values()), 6)
        moved = sum(v for (a, b), v in sharding.transfers(old, want).items() if a != b)
        assert moved == sum(max(0, old[i] - want[i]) for i in old)
    blocks = {(i, k): rng.randint(1, 100) for i in range(4) for k in range(200)}
    to = sharding.place_blocks(blocks, cap := sharding.even_capacities(sum(blocks.values()), 4))
    held = Counter()
    for b, j in to.items():
        held[j] += blocks[b]
    assert all(abs(held[j] - cap[j]) <= 2 for j in cap)


def test_rewrite_touches_what_moved(docs, tmp_path):
    plan = sharding.op2_sharding(docs.where("doc_id is not null").dropDuplicates(["doc_id"]))
    touched = sharding.rewrite(docs.dropDuplicates(["doc_id"]).where("doc_id is not null"), plan, f"file://{tmp_path}/out")
    want = {r["shard"] for r in plan.where("shard <> old_shard").select("shard").union(plan.where("shard <> old_shard").select("old_shard")).collect()}
    assert {r["shard"] for r in touched.collect()} == want


def test_shards_are_written_whole(spark, docs, tmp_path):
    from pyspark.sql import functions as F

    old = F.crc32(F.coalesce(F.col("source"), F.lit("")).cast("binary")) % 16
    twice = docs.union(docs.where("doc_id is null or doc_id < 5"))
    placed = sharding.reshard(twice, old, f"file://{tmp_path}/out").collect()
    names = docs.columns
    assert Counter(tuple(r[c] for c in names) for r in placed) == Counter(map(tuple, twice.collect()))
    written = spark.read.parquet(f"file://{tmp_path}/out").select(*names, "shard", "slot").collect()
    touched = {r["shard"] for r in written}
    assert touched and Counter(map(tuple, written)) == Counter(tuple(r[c] for c in [*names, "shard", "slot"]) for r in placed if r["shard"] in touched)
    sharding.rewrite(twice, sharding.op2_sharding(twice), f"file://{tmp_path}/again")
    again = spark.read.parquet(f"file://{tmp_path}/again").select("shard", "slot").collect()
    assert len(again) == len(set(again)) == len(written)
    stay = sharding.reshard(docs, F.lit(0), f"file://{tmp_path}/stay", shards=1)
    assert stay.count() == docs.count() and spark.read.schema("doc_id long").parquet(f"file://{tmp_path}/stay").count() == 0


def water_fill(sizes, weights, epochs):
    """The loop that clamps and reshares, as it is usually told."""
    total, target, clamped = sum(sizes.values()), {}, set()
    while True:
        rest = total - sum(epochs * sizes[s] for s in clamped)
        left = sum(weights[s] for s in sizes if s not in clamped)
        target = {s: epochs * sizes[s] if s in clamped else rest * weights[s] / left for s in sizes}
        over = {s for s in sizes if s not in clamped and target[s] > epochs * sizes[s]}
        if not over:
            return target
        clamped |= over


def test_mix(docs):
    rows = mixing.op3_mixing(docs).collect()
    size = lambda t: len(WORD.findall(t or ""))
    sizes = Counter()
    for r in documents():
        sizes[r[3]] += size(r[1])
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    target = water_fill(sizes, {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}, 3)
    taken, largest = Counter(), Counter()
    for r in rows:
        assert r["source_size"] == sizes[r["source"]] and r["target"] == pytest.approx(target[r["source"]])
        assert 0 <= r["taken"] <= 3 * r["size"]
        taken[r["source"]] += r["taken"]
        largest[r["source"]] = max(largest[r["source"]], r["size"])
    assert all(abs(taken[s] - target[s]) <= largest[s] for s in sizes)
    assert sorted(map(str, rows)) == sorted(map(str, mixing.op3_mixing(docs).collect()))
    whole = Counter(r["doc_id"] for r in mixing.mix(docs).collect())
    assert sum(whole.values()) == sum(r["reps"] for r in rows)
    assert mixing.mix(docs).columns == docs.columns


def test_tokens_are_those_of_the_tokenizer():
    import public_tokenizers
    from tokenizers import Tokenizer

    own, theirs = packing.Tokens(), Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    rng = random.Random(2)
    texts = [r[1] or "" for r in documents() if r[0] != 105] + ["".join(rng.choice(" \n\tab1é'<|>.") for _ in range(rng.randint(0, 60))) for _ in range(400)]
    for t in texts:
        assert np.frombuffer(own(t), "<u4").tolist() == theirs.encode(t, add_special_tokens=False).ids


def test_long_runs_are_tokenized_exactly():
    import public_tokenizers
    from tokenizers import Tokenizer

    own, theirs = packing.Tokens(), Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    rng = random.Random(8)
    texts = ["".join(rng.choice([" ", "\n", "\t", "a", "word", "1", "-"]) * rng.choice([1, 2, 3, 400, 9000]) for _ in range(30)) for _ in range(40)]
    texts += [" " * 1_200_000 + "end", "a" + "\n" * 1_000_000, " \n" * 500_000 + " b  c"]
    for t in texts:
        assert np.frombuffer(own(t), "<u4").tolist() == theirs.encode(t, add_special_tokens=False).ids


def test_buckets_are_packed_apart_and_whole(docs):
    rows = packing.sequences(docs, bucket=16).collect()
    parts = [(r["sequence_id"], p) for r in rows for p in r["parts"]]
    assert len(rows) == len({r["sequence_id"] for r in rows})
    want = Counter()
    own = packing.Tokens()
    for r in documents():
        n = len(own(r[1] or "")) // 4 + 1
        want.update((r[0], k, s, m) for k, (s, m) in enumerate(packing.cut_points(n)))
    assert Counter((p["doc_id"], p["piece"], p["start"], p["length"]) for _, p in parts) == want
    for r in rows:
        at = 0
        for p in r["parts"]:
            assert p["offset"] == at
            at += p["length"]
        assert len(r["ids"]) == 4 * at <= 4 * 2048
    assert packing.widened(packing.narrowed(np.array([0, 65535, 7], "<u4").tobytes())) == np.array([0, 65535, 7], "<u4").tobytes()
    assert packing.widened(packing.narrowed(np.array([0, 65536], "<u4").tobytes())) == np.array([0, 65536], "<u4").tobytes()


def test_slices_lose_no_row():
    import pandas as pd

    from huecount.llm.common import SLICE_CHARS, slices

    texts = ["a" * n for n in (5, SLICE_CHARS, 1, 0, SLICE_CHARS + 9)] + [None] * 300 + ["b"] * 300
    parts = list(slices([pd.DataFrame({"text": texts[:0]}), pd.DataFrame({"text": texts})]))
    assert [t for p in parts for t in p["text"]] == texts and max(map(len, parts)) <= 256
    assert all(len(p) == 1 or p["text"].str.len().sum() <= SLICE_CHARS for p in parts)


def test_letters():
    assert [langid.has_letter(t) for t in ("½ ² Ⅷ _ 12", "½a", "日", "", None, "\n.,", "ª")] == [False, True, True, False, False, False, True]


def test_tokens_keep_no_words():
    import public_tokenizers
    from tokenizers import Tokenizer

    own, theirs = packing.Tokens(), Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for text in ("", " ", "one two  three ", " lead", "a\n b\t c", "x" * 5000, "wörd " * 300, "<|endoftext|> a"):
        assert np.frombuffer(own(text), "<u4").tolist() == theirs.encode(text, add_special_tokens=False).ids
    assert not any(isinstance(x, dict) for x in vars(own).values()) and not hasattr(own, "part")


def test_packing(docs):
    rows = packing.op4_packing(docs).collect()
    own, space = packing.Tokens(), defaultdict(list)
    for r in rows:
        space[r["sequence_id"]].append((r["offset"], r["length"]))
    for parts in space.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= 2048
    want = Counter()
    for r in documents():
        ids = own(r[1] or "") + bytes(4)
        for k, (s, n) in enumerate(packing.cut_points(len(ids) // 4)):
            want[r[0], k, s, n, zlib.crc32(ids[4 * s : 4 * (s + n)])] += 1
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows) == want
    assert len(space) <= -(-sum(r["length"] for r in rows) // 2048) + 1


def test_sequences_hold_the_ids(spark, docs):
    from huecount.llm import pipeline

    own, want = packing.Tokens(), Counter()
    for r in documents():
        want[r[0], own(r[1] or "") + bytes(4)] += 1
    whole = {r["sequence_id"]: bytes(r["ids"]) for r in packing.sequences(docs).collect()}
    rows = pipeline.packed(spark, docs, "").collect()
    space, texts = defaultdict(list), defaultdict(list)
    for r in rows:
        assert len(r["ids"]) == 4 * r["length"]
        space[r["sequence_id"]].append((r["offset"], bytes(r["ids"])))
        texts[r["doc_id"], r["piece"]].append(bytes(r["ids"]))
    assert all(len(x) <= 4 * 2048 for x in whole.values()) and len(space) == len(whole)
    assert all(parts == sorted(parts) for parts in space.values())
    assert sorted(map(len, whole.values())) == sorted(sum(len(x) for _, x in parts) for parts in space.values())
    got = Counter()
    for (doc, piece), found in texts.items():
        if piece == 0:  # repeats are equal here, so any piece of the same number continues a text
            for k, ids in enumerate(found):
                more = [texts[doc, p][k] for p in range(1, len(texts)) if (doc, p) in texts]
                got[doc, b"".join([ids, *more])] += 1
    assert got == want


def test_fullest_bin_is_the_fullest():
    rng = random.Random(3)
    for _ in range(60):
        items = [rng.randint(1, 30) for _ in range(rng.randint(1, 9))]
        counts = [0] * 41
        for n in items:
            counts[n] += 1
        got, rest = packing.fullest(counts, 40), sorted(items)[:-1]
        sums = {0}
        for n in rest:
            sums |= {s + n for s in sums if s + n + max(items) <= 40}
        assert sum(got) == max(items) + max(sums) and not Counter(got) - Counter(items)
    packed = packing.pack_histogram(Counter(rng.randint(1, 100) for _ in range(500)), 100)
    assert sum(sum(one.values()) * t for one, t in packed) == 500 and all(sum(n * c for n, c in one.items()) <= 100 for one, _ in packed)


def brute_counts(text):
    text = text or ""
    words = WORD.findall(text)
    windows = defaultdict(list)
    for i in range(len(words) - 4):
        windows[tuple(words[i : i + 5])].append(i)
    covered = {i + k for at in windows.values() if len(at) > 1 for i in at for k in range(5)}
    lines = [x for x in text.split("\n") if WORD.search(x)]
    return len(words), sum(map(len, words)), sum(text.count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(covered), len(lines)


def test_quality(docs):
    texts = [r[1] for r in documents()] + ["a b c d e f a b c d e f a", "x\n\nx\n x\n", "| a # | b", "a\x0bb\x0cc\xa0d\x85e", "one two three four five one two three four five"]
    known = minhash.WordHash()
    for t in texts:
        assert quality.counts_of(t, known) == brute_counts(t)
    rows = {r["doc_id"]: r for r in quality.op5_quality(docs).collect()}
    assert rows[102]["base_failed"] and rows[105]["base_failed"] and not rows[105]["kept"]
    assert all(rows[i]["kept"] for i in range(60)) and not any(r["kept"] and r["base_failed"] for r in rows.values())


def test_thresholds_come_from_the_group(spark):
    plain = " ".join(f"word{i}" for i in range(40))
    rows = [(i, plain, "en", "a") for i in range(150)] + [(500, plain.replace("word1", "#*#*"), "en", "a")]
    rows += [(1000 + i, plain.replace("word1", "#*#*"), "en", "b") for i in range(150)] + [(2000, plain, None, None)]
    kept = {r["doc_id"]: r["kept"] for r in quality.op5_quality(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).collect()}
    assert not kept[500] and kept[1000] and kept[0] and kept[2000]


def test_each_measure_rejects(spark):
    rng = random.Random(7)
    text = lambda n=60: [f"w{rng.randrange(10**6):06d}" for _ in range(n)]
    lines = lambda words: "\n".join(" ".join(words[i : i + 4]) for i in range(0, len(words), 4))
    rows = [(i, lines(text()), "en", "a") for i in range(300)]
    base = text(57)
    rows += [(1000, lines(["#$%#$%#", *text(59)]), "en", "a"), (1001, lines([w + "xx" for w in text()]), "en", "a")]
    rows += [(1002, "\n".join(["ok"] * 8 + [" ".join(base[i : i + 4]) for i in range(0, 48, 4)]), "en", "a")]
    rows += [(1003, lines(base + base[10:15]), "en", "a"), (1004, lines([w[1:5] for w in text()]), "en", "a")]
    got = {r["doc_id"]: r for r in quality.op5_quality(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).collect()}
    assert not any(r["base_failed"] for r in got.values()) and all(got[i]["kept"] for i in range(300))
    assert sorted(i for i in got if not got[i]["kept"]) == [1000, 1001, 1002, 1003, 1004]
    failing = lambda i: {m for m, (a, b, *_) in quality.MEASURES.items() if got[i][a] / got[i][b] > {"symbols": 0.01, "word_length": 8, "repeated_lines": 0.2, "repeated_words": 0.1}[m]}
    assert failing(1000) == {"symbols"} and failing(1001) == {"word_length"} and "repeated_lines" in failing(1002) and failing(1003) == {"repeated_words"}


def test_sketch_quantiles_are_within_their_error(spark):
    from pyspark.sql import functions as F

    values = [random.Random(1).lognormvariate(0, 1) for _ in range(0)] or [1.013**i for i in range(400)]
    rows = spark.createDataFrame([(0, float(v)) for v in values], "level int, x double")
    bucket = F.ceil(F.round(F.log("x") / float(np.log(quality.GAMMA)), 9)).cast("int")
    sketch = rows.select("level", F.lit("l").alias("lang"), F.lit("s").alias("source"), F.lit("m").alias("measure"), bucket.alias("bucket")).groupBy("level", "lang", "source", "measure", "bucket").agg(F.count("*").alias("n"))
    q = quality.quantiles(sketch).first()["q"]
    assert q[0] == pytest.approx(values[99], rel=0.011) and q[1] == pytest.approx(values[299], rel=0.011)


def shingle_set(text):
    """Shingles, each with the number of its occurrences so far: sets of these are as alike as the weighted sets."""
    w, seen = (text or "").encode().split(), Counter()
    n, out = min(5, len(w)), set()
    for i in range(len(w) - n + 1 if w else 0):
        s = tuple(w[i : i + n])
        out.add((s, seen[s]))
        seen[s] += 1
    return frozenset(out)


def brute_classes(texts, threshold=0.8):
    sets = {i: shingle_set(t) for i, t in texts.items()}
    root = {i: i for i in texts}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(i for i in texts if sets[i])
    for x, a in enumerate(ids):
        for b in ids[x + 1 :]:
            both = len(sets[a] & sets[b])
            if both >= threshold * (len(sets[a]) + len(sets[b]) - both):
                ra, rb = find(a), find(b)
                root[max(ra, rb)] = min(ra, rb)
    return {i: find(i) for i in texts}


def test_near_duplicates(spark, docs):
    rng = random.Random(9)
    base = [f"w{i}" for i in range(300)]
    rows = [(r[0], r[1]) for r in documents() if r[0] is not None]
    for i in range(40):  # near copies of a text, near to each other only through it
        copy = base[:]
        for k in rng.sample(range(300), 4):
            copy[k] = f"c{i}_{k}"
        rows.append((200 + i, " ".join(copy)))
    rows.append((199, " ".join(base)))
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r["class_id"] for r in minhash.near_duplicates(frame).collect()}
    assert got == brute_classes(dict(rows))
    assert got[101] == 3 and got[100] == 0 and got[102] == 102 and got[103] == 103
    kept = minhash.deduplicated(docs)
    ids = Counter(r["doc_id"] for r in kept.collect())
    assert ids[7] == 1 and ids[100] == 0 and ids[101] == 0 and ids[3] == 1 and ids[None] == 1 and kept.columns == docs.columns


def test_darts_estimate_weighted_similarity():
    rng = np.random.default_rng(0)
    agree, true = [], []
    for _ in range(60):
        e = rng.integers(0, 2**63, 50).astype(np.uint64)
        a, b = rng.exponential(2, 50), rng.exponential(2, 50)
        s = minhash.dart_signatures([(e, a), (e, b)], 160)
        agree.append((s[0] == s[1]).mean())
        true.append(np.minimum(a, b).sum() / np.maximum(a, b).sum())
    assert abs(np.mean(agree) - np.mean(true)) < 0.02


def test_repeated_ids_and_hot_texts(spark):
    rng = random.Random(12)
    text = lambda k: " ".join(f"t{k}_{rng.randrange(9)}_{i}" for i in range(40))
    a, b, c = text(0), text(1), text(2)
    rows = [(1, a), (1, b), (2, b), (3, b), (2, c), (None, c), (None, None), (None, ""), (9, None), (9, None), (5, "x y"), (None, "x y"), (None, "q r s"), (None, "q r s")]
    rows += [(100 + i, a) for i in range(300)] + [(1, a)] * 20 + [(4, c + " more")]
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(7)
    got = Counter((r["doc_id"], r["class_id"]) for r in minhash.near_duplicates(frame).collect())
    want = Counter({(1, 1): 22, (2, 1): 1, (3, 1): 1, (2, 2): 1, (None, 2): 1, (4, 2): 1, (None, None): 4, (9, 9): 2, (5, 5): 1, (None, 5): 1})
    want.update({(100 + i, 1): 1 for i in range(300)})
    assert got == want
    kept = Counter(tuple(r) for r in minhash.deduplicated(frame).collect())
    assert kept == Counter([(1, a), (1, b), (2, c), (None, None), (None, ""), (9, None), (9, None), (5, "x y"), (None, "q r s")])


def test_weights_decide(spark):
    base = [f"w{i}" for i in range(40)]
    lines = [" ".join(base), " ".join(base + base[:20]), " ".join(base * 3), " ".join(base[:39] + ["other"])]
    got = {r["doc_id"]: r["class_id"] for r in minhash.near_duplicates(spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string")).collect()}
    assert got == brute_classes(dict(enumerate(lines))) == {0: 0, 1: 1, 2: 2, 3: 0}


def test_no_link_is_lost_on_given_documents(spark):
    frame = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    texts = {r["doc_id"]: r["text"] for r in frame.collect()}
    got = {r["doc_id"]: r["class_id"] for r in minhash.near_duplicates(frame).collect()}
    assert got == brute_classes(texts) and sum(k != v for k, v in got.items()) > 20


def test_large_buckets_meet_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(minhash, "BLOCK", 256)
    base = [f"w{i}" for i in range(100)]
    texts = [(i, " ".join(base[:90] + [f"x{i}"])) for i in range(600)] + [(600, " ".join(base[:90])), (601, " ".join(base[40:]))]
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    nodes = minhash.cut(minhash.signed(docs).withColumns({"node": minhash.F.col("doc_id"), "cells": minhash.F.col("n")}), "test")
    members = spark.createDataFrame([(7, i, 602) for i in range(602)], "key long, node long, n long")
    labels = spark.createDataFrame([(i, 0) for i in range(600)], "node long, label long")
    pairs, links = minhash._cross_pairs(members, labels, nodes, docs, 0.8)
    assert pairs.count() == 0 and {(r["b"], r["a"] < 600) for r in links.collect()} == {(600, True)}
    sig = [bytes(r["sig"]) for r in nodes.where("node < 8").orderBy("node").collect()]
    one = minhash.agreements(sig, sig[:3])
    assert one.shape == (8, 3) and one[0, 0] == 1 and one[3, 1] == sum(sig[3][i : i + 2] == sig[1][i : i + 2] for i in range(0, 320, 2)) / 160
    sets = [np.unique(minhash.shingles(t, minhash.WordHash())) for _, t in texts[595:]]
    want = [[len(set(x) & set(y)) / len(set(x) | set(y)) for y in sets] for x in sets]
    assert np.allclose(minhash.similarities(sets, sets, 7), want, atol=1e-6)


def test_components(spark):
    chain = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101)], "a long, b long")
    got = {r["node"]: r["label"] for r in minhash.components(chain).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100}


def test_language(spark):
    rng = random.Random(4)
    words = {"aa": ["bada", "gada", "dabag"], "bb": ["sheis", "thesi", "heish"]}
    rows = [(i, " ".join(rng.choice(words[k]) for _ in range(rng.randint(3, 60))), k) for i in range(300) for k in [("aa", "bb")[i % 2]]]
    extra = [(1000, None, "aa"), (1001, "123 456 !", "aa"), (1002, "bada gada " * 900, None)]
    frame = spark.createDataFrame(rows + extra, "doc_id long, text string, lang string")
    got = {r["doc_id"]: r for r in langid.op1_language_id(frame).collect()}
    assert all(got[i]["held_out"] == (zlib.crc32(str(i).encode()) % 4 == 2) for i in got)
    held = [i for i, _, _ in rows if got[i]["held_out"]]
    assert sum(got[i]["lang_pred"] == ("aa", "bb")[i % 2] for i in held) >= 0.97 * len(held)
    assert (got[1000]["lang_pred"], got[1001]["lang_pred"], got[1002]["lang_pred"]) == ("und", "und", "aa")
    assert all(0 <= r["score"] <= 1 for r in got.values())
    assert {r[0] for r in langid.identified(frame).select("doc_id").collect()} >= {1002} and langid.identified(frame).where("doc_id in (1000, 1001)").count() == 0


def test_network_gradients_and_prediction_path():
    m = langid.ByteGru(["a", "b", "c"], hidden=4)
    rng = np.random.default_rng(1)
    x, y = rng.integers(0, 256, (6, 5)), np.array([0, 1, 2, 1, 0])
    f, _ = m._layer("f", x)
    assert np.allclose(f, m._states("f", x, None), atol=1e-5)
    m.p = {k: v.astype(np.float64) for k, v in m.p.items()}
    _, g = m.gradients(x, y)
    for k in ("fU", "fC", "bU", "bC", "W"):
        at = tuple(rng.integers(0, s) for s in m.p[k].shape)
        m.p[k][at] += 1e-2
        up = m.gradients(x, y)[0]
        m.p[k][at] -= 2e-2
        down = m.gradients(x, y)[0]
        m.p[k][at] += 1e-2
        assert g[k][at] == pytest.approx((up - down) / 2e-2, rel=1e-2, abs=1e-6)
    texts = [b"abc", b"", b"x" * 200]
    alone = np.concatenate([m.documents([t]) for t in texts])
    assert np.allclose(m.documents(texts), alone, atol=1e-5)


def brute_secrets(text):
    found = []
    for m in re.finditer(r"""(?ai)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text):
        if len(m[2]) >= 12:
            found.append((m.start(), 0, m.end(), "assign"))
    for k, (kind, p, n) in enumerate((("access", r"AKIA[A-Z0-9]+", 18), ("hex", r"[0-9a-f]+", 16)), 1):
        found += [(m.start(), k, m.end(), kind) for m in re.finditer(p, text) if len(m[0]) >= n]
    return ",".join(f"{kind}:{a}:{b}" for a, _, b, kind in sorted(found))


def test_secrets(spark):
    rng = random.Random(8)
    bits = ["password", "Token", "api_key", "=", ":", " ", '"', "AKIA", "ABCDEFGH12345678", "deadbeef00112233", "x", "\n", "é", "secret"]
    texts = ["".join(rng.choice(bits) for _ in range(rng.randint(0, 25))) for _ in range(300)] + [None, "", "token=secret: abcdefghijklm"]
    rows = secrets.op10_secret_scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    for r in rows:
        want = brute_secrets(texts[r["doc_id"]] or "")
        assert r["base_sha256"] == hashlib.sha256(want.encode()).hexdigest()
        assert set(filter(None, want.split(","))) <= set(r["spans"].split(",")) | {""}
        assert r["n_assign"] == want.count("assign") and r["n_access"] == want.count("access") and r["n_hex"] == want.count("hex")


def test_assignments_are_followed():
    value = lambda t: [t[a:b] for a, b, k in secrets.scan(t) if k == "literal"]
    assert value('base = "A1b2C3d4"\nclient_secret = base') == ["A1b2C3d4"]
    assert value("export DB_PASSWD='Tr0ub4dor&3'") == ["Tr0ub4dor&3"]
    assert value('{"private_key": "Zx81-kq77-PPq"}') == ["Zx81-kq77-PPq"]
    assert value('config["db_password"] = "P4ssw0rd!xyz"') == ["P4ssw0rd!xyz"]
    assert value("<password>s3cr3t-Pass99</password>") == ["s3cr3t-Pass99"]
    for clean in ('password = "changeme"', 'token_count = "12345abcXYZ"', "the secret: nobody knows it", 'password == "Abc123!xyz"', "key: value"):
        assert value(clean) == []
    assert secrets.redact("a token=abcdefghijkl1 b", secrets.scan("a token=abcdefghijkl1 b")) == "a token=[secret] b"


def test_whole_literals_are_found():
    value = lambda t: [t[a:b] for a, b, k in secrets.scan(t) if k == "literal"]
    for line in ('session_cookie = "Zq7RmX2vKp9LwT4nBs6Y"', 'pass_word- = "Zq7RmX2vKp9LwT4nBs6Y"'):
        assert value(line) == value(line + "\nthe author of a keyboard") == ["Zq7RmX2vKp9LwT4nBs6Y"]
    assert value('prefix = "sk_live_"\nclient_secret = prefix + "A8f3kQ9zLm2XvR7t"') == ["sk_live_", "A8f3kQ9zLm2XvR7t"]
    assert value('end = "A8f3kQ9zLm2XvR7t"\nclient_secret = "sk_live_" + end') == ["A8f3kQ9zLm2XvR7t", "sk_live_"]
    assert value('client_secret = unknown() + x\nclient_secret = other + "A8f3kQ9zLm2XvR7t"') == ["A8f3kQ9zLm2XvR7t"]
    long = "A8f3kQ9zLm2XvR7t" * 400
    assert value(f'client_secret = "{long}"') == [long]
    parts = [f"A8f3kQ{i:02d}" for i in range(30)]
    assert value("client_secret = " + " + ".join(f'"{p}"' for p in parts)) == parts
    assert value("x" * 200 + '_password = "P4ssw0rd!xyz"') == ["P4ssw0rd!xyz"]
    pem = r"-----BEGIN RSA PRIVATE KEY-----\nMIIEpAIBAAKCAQEA\n-----END RSA PRIVATE KEY-----"
    assert value(f'{{"private_key": "{pem}"}}') == [pem]
    block = "-----BEGIN PRIVATE KEY-----\n  MIIEpAIBAAKCAQEA\n  Zx81kq77PPq+/=\n  -----END PRIVATE KEY-----"
    for before, after in (("private_key: |\n  ", "\nnext: 1"), ('tls_key = """', '"""'), ("private_key := `", "`"), ("private_key:\n  ", "")):
        assert value(before + block + after) == [block]
    assert value("signing_key: |\n  " + block.replace("PRIVATE", "PUBLIC")) == []
    assert value('wallet_passphrase = "correct horse battery staple"') == ["correct horse battery staple"]
    assert value('user = "bob" password = "P4ssw0rd!xyz"') == ["P4ssw0rd!xyz"]
    assert value('{"password": "Please enter your new password"}') == []
    doubled = 'secret = "A8f3kQ9z"\n' + "secret = secret + secret\n" * 60
    assert value(doubled) == ["A8f3kQ9z"]


def test_cheap_test_loses_nothing():
    rng = random.Random(12)
    bits = ["session", "cookie", "_", "api", "access", "pin", "client", "pass", "word", "-", " ", "=", ":", '"Zq7RmX2vKp9LwT4nBs6Y"', "'a8F3-kQ9z'", "+", "\n", "<pin_key>", "Zq7RmX2vKp9L", "</pin_key>"]
    for _ in range(3000):
        t = "".join(rng.choice(bits) for _ in range(rng.randint(1, 14)))
        want = {p for n, v, places in secrets.name_literal_pairs(t) if secrets.name_score(n) >= 2 and secrets.name_score(n) + secrets.literal_score(v) >= secrets.REPORT_FROM for p in places}
        assert {(a, b) for a, b, k in secrets.scan(t) if k == "literal"} == {(a, b) for a, b in want if b > a}
