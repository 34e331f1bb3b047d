"""The corpus pipeline, stage by stage against plain versions, and the sizes of texts that operators stand."""

import time
import zlib
from collections import Counter, defaultdict

from huecount.llm import langid, minhash, mixing, packing, quality, secrets, sharding
from huecount.llm.common import fresh_dir
from huecount.llm.pipeline import STAGES, run
from huecount.session import made, release
from tests.conftest import SF
from tests.llm.test_documents import SCHEMA, WORD, brute_classes, documents, water_fill


def staged(spark, df):
    path = fresh_dir(spark, "test-stage")
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def test_stages_equal_plain_versions(spark):
    extra = [(200 + i, f"token = 'Zq7RmX2vKp9LwT4nBs6Y{i}' and " + " ".join(f"plain{i}x{k}" for k in range(30)), "en", "s9", 1, 0, 0, None) for i in range(3)]
    docs = staged(spark, spark.createDataFrame([r for r in documents() if r[0] is not None] + extra, SCHEMA))
    (_, language), (_, near), (_, secret), (_, mixed), (_, packed) = STAGES
    known = staged(spark, language(spark, docs, ""))
    model = langid.fitted(docs, ~langid.held_out())
    want = Counter()
    for r in docs.collect():
        if langid.has_letter(r["text"]) and model.documents([r["text"].encode()]).max() >= 0.3:
            want[tuple(r)] += 1
    assert Counter(map(tuple, known.collect())) == want and known.columns == docs.columns
    one = staged(spark, near(spark, known, ""))
    rows = {r["doc_id"]: tuple(r) for r in known.collect()}
    classes = brute_classes({i: r[1] for i, r in rows.items()})
    assert Counter(map(tuple, one.collect())) == Counter(r for i, r in rows.items() if classes[i] == i)
    clean = staged(spark, secret(spark, one, ""))
    want = Counter()
    for r in one.collect():
        text = secrets.redact(r["text"], secrets.scan(r["text"]))
        want[(r["doc_id"], text, r["lang"], r["source"], len(text), *r[5:])] += 1
    assert Counter(map(tuple, clean.collect())) == want and sum("[secret]" in r[1] for r in want) == 3
    mix = staged(spark, mixed(spark, clean, ""))
    given, sizes, got, largest = {r["doc_id"]: r for r in clean.collect()}, Counter(), Counter(), Counter()
    for r in given.values():
        n = len(WORD.findall(r["text"]))
        sizes[r["source"]] += n
        largest[r["source"]] = max(largest[r["source"]], n)
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    target = water_fill(sizes, {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}, 3)
    times = Counter(r["doc_id"] for r in mix.collect())
    for i, n in times.items():
        got[given[i]["source"]] += n * len(WORD.findall(given[i]["text"]))
    assert all(tuple(r) == tuple(given[r["doc_id"]]) for r in mix.collect()) and max(times.values()) <= 3
    assert all(abs(got[s] - target[s]) <= largest[s] for s in sizes)
    out, tokens, found = packed(spark, mix, "").collect(), packing.Tokens(), Counter()
    for r in out:
        found[r["doc_id"], r["piece"], r["start"], r["length"], zlib.crc32(r["ids"])] += 1
    want = Counter()
    for r in mix.collect():
        ids = tokens(r["text"]) + bytes(4)
        want.update((r["doc_id"], k, s, n, zlib.crc32(ids[4 * s : 4 * (s + n)])) for k, (s, n) in enumerate(packing.cut_points(len(ids) // 4)))
    assert found == want


def test_run_is_the_stages_and_leaves_one_table(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    mark = made()
    out = run(spark, SF)
    assert made() == mark + 1
    n = out.count()
    assert n > 0 and out.where("offset + length > 2048").count() == 0 and out.select("doc_id").distinct().count() < docs.count()
    assert release(spark, mark) == 1 and made() == mark


def test_run_on_an_empty_table(spark, tmp_path):
    spark.createDataFrame([], SCHEMA).write.parquet(f"file://{tmp_path}/documents.parquet")
    assert run(spark, f"file://{tmp_path}").count() == 0


LONG = 10_000_000
TEXTS = {"blanks": " " * LONG, "lines": "\n" * LONG, "letters": "a" * LONG, "words": "ab cd " * (LONG // 6), "quotes": '"' * LONG, "names": "secret=" * (LONG // 7), "base": "A" * (LONG // 2) + "=" * (LONG // 2)}


def test_texts_of_ten_megabytes(spark):
    texts = dict(enumerate([*TEXTS.values(), "some short words"]))
    docs = spark.createDataFrame([(i, t, "en" if i % 2 else "de", "s", len(t), 0, 0, None) for i, t in texts.items()], SCHEMA)
    n = {i: len(WORD.findall(t)) for i, t in texts.items()}
    began = time.perf_counter()
    assert {r["doc_id"]: r["lang_pred"] != "und" for r in langid.op1_language_id(docs).collect()} == {i: langid.has_letter(t) for i, t in texts.items()}
    assert {r["doc_id"]: r["size"] for r in sharding.op2_sharding(docs).collect()} == {i: len(t) + 1 for i, t in texts.items()}
    assert {r["doc_id"]: r["size"] for r in mixing.op3_mixing(docs).collect()} == n
    assert {r["doc_id"]: r["n_words"] for r in quality.op5_quality(docs).collect()} == n
    assert {r["doc_id"]: r["class_id"] for r in minhash.op6_near_duplicates(docs).collect()} == {i: i for i in texts}
    assert {r["doc_id"] for r in secrets.op10_secret_scan(docs).collect()} == set(texts)
    pieces = {r[0]: r[1] for r in packing.op4_packing(docs).groupBy("doc_id").agg({"length": "sum"}).collect()}
    assert set(pieces) == set(texts) and min(pieces[i] for i in range(len(TEXTS))) > 1 and time.perf_counter() - began < 600


def test_sharding_keeps_its_law(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    held, shard = Counter(), defaultdict(set)
    for r in sharding.op2_sharding(docs).collect():
        assert r["law"] == "bytes" and r["grown_shard"] is None
        held[r["shard"]] += r["size"]
        shard[r["shard"]].add(r["slot"])
    biggest = max(len((r["text"] or "").encode()) + 1 for r in docs.collect())
    mean = sum(held.values()) / 16
    assert len(held) == 16 and all(abs(x - mean) <= max(biggest, 0.02 * mean) for x in held.values())
    assert all(x == set(range(len(x))) for x in shard.values())


def test_no_text_passes_the_epochs(spark):
    rows = [(i, "w " * 50, "en", "big") for i in range(200)] + [(1000 + i, "w " * (i % 3), "en", "small") for i in range(60)] + [(2000, "", "en", "none")]
    out = mixing.op3_mixing(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).collect()
    capped = [r for r in out if r["source"] == "small"]
    assert {r["reps"] for r in capped} == {3} and all(r["reps"] == 0 for r in out if r["source"] == "none")
    assert max(r["reps"] for r in out) <= 3
