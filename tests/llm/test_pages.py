"""Operators on pages and embeddings, the pipeline and the registered queries."""

import hashlib
import random
from collections import defaultdict

import duckdb
import numpy as np
import pandas as pd
import pytest

from huecount.llm import html, queries, topk, warc
from tests.conftest import SF

SCHEMA = "page_id long, url string, html string, source string"


def pages(spark):
    big = "<p>" + "x" * 200 + "</p>"
    rows = [(i, f"http://h{i % 3}.example.com/p/{i}", f"<html><body><nav>menu</nav><article><h1>T{i}</h1><p>a  b&amp;c<p>second <i>one</i></article><footer>f</footer></body></html>", "s") for i in range(9)]
    rows += [(20, "http://x.com/a", big, None), (21, "https://X.com:443/b?q=1#f", big, None), (22, None, None, None), (23, "not a url", "", None), (24, "http://x.com/a", "tiny", None), (25, "http://x.com/c", "tiny", None), (None, "http://x.com/d", big, None)]
    return spark.createDataFrame(rows + [rows[0]], SCHEMA)


def test_warc(spark):
    rows = warc.op8_warc(pages(spark)).collect()
    assert len(rows) == 17
    by = {r["page_id"]: r for r in rows}
    given = {r["page_id"]: r["html"] for r in pages(spark).collect()}
    for p, r in by.items():
        raw = (given[p] or "").encode()
        assert r["payload_bytes"] == len(raw) and r["payload_digest"] == hashlib.sha256(raw).hexdigest()
    assert by[21]["record_type"] == "revisit" and by[21]["refers_to"] == 20 and by[20]["record_type"] == "response"
    assert by[25]["record_type"] == "response" and by[None]["refers_to"] == 20
    assert warc.url_key("https://X.com:443/b?q=1#f") == "com,x)/b?q=1"
    assert warc.op8_warc(spark.createDataFrame([], SCHEMA)).count() == 0


def test_loser_tree():
    rng = random.Random(6)
    for n in (0, 1, 2, 3, 7, 16, 21):
        runs = [sorted(rng.randrange(40) for _ in range(rng.randrange(8))) for _ in range(n)]
        assert list(warc.LoserTree([iter(r) for r in runs])) == sorted(x for r in runs for x in r)


def test_external_merge(spark, tmp_path):
    rng = random.Random(9)
    folder, runs, want = f"file://{tmp_path}", [], []
    from pyarrow import fs

    system, path = fs.FileSystem.from_uri(folder)
    for k in range(11):
        rows = [(str(rng.randrange(60)) if rng.random() > 0.1 else None, "u", f"com,{rng.choice('abc')})/", f"2024-01-0{rng.randint(1, 3)}", 1, "d", "response", None, f"a{k}", i, 1) for i in range(rng.choice([0, 1, 300, 900]))]
        rows.sort(key=warc.key_of)
        want += rows
        assert warc.write_run(system, f"{path}/r{k:02d}", iter(rows)) == len(rows)
        runs.append((f"r{k:02d}", len(rows)))
        run = warc.Run(system, f"{path}/r{k:02d}")
        low, high = ("com,a)/", "2024-01-02", 7), ("com,b)/", "2024-01-03", -1)
        assert list(run.within()) == rows and list(run.within(low, high)) == [r for r in rows if low <= warc.key_of(r) < high]
    table = spark.createDataFrame(runs, warc.RUN)
    for fan_in, size in ((1024, 10**9), (3, 200), (2, 500)):
        index = warc.merged_index(table, folder, fan_in, size)
        got = [tuple(r) for r in index.toLocalIterator()]
        assert [warc.key_of(r) for r in got] == sorted(map(warc.key_of, want)) and sorted(map(repr, got)) == sorted(map(repr, want))
        assert (index.rdd.getNumPartitions() > 3) == (size < 10**6)


def test_records_have_names_of_their_own():
    a = [warc.parsed(warc.record_bytes(n, p, "u", warc.stamp(None), b"x" * 3, "d", r))[0] for n, p, r in (("page:1", "1", None), ("place:0/1/0/0", None, "1"), ("place:0/1/0/1", None, "1"))]
    assert len({x["WARC-Record-ID"] for x in a}) == 3 and a[1]["WARC-Refers-To"] == a[0]["WARC-Record-ID"] and "Page-Id" not in a[1]


def test_history_is_in_order(spark):
    rows = [(r["url_key"], r["captured_at"]) for r in warc.op8_warc(pages(spark).where("page_id is not null")).toLocalIterator()]
    assert rows == sorted(rows)


def test_html(spark):
    got = {r["page_id"]: r for r in html.op7_html(pages(spark)).collect()}
    assert got[1]["text"] == "T1\na b&c\nsecond one" and got[22]["text"] == "" and got[23]["n_chars"] == 0
    assert got[24]["text"] == "tiny" and len(got) == 16
    assert html.op7_html(spark.createDataFrame([], SCHEMA)).count() == 0
    page = '<div class="menu"><a href=x>m</a></div><main><header>H</header><h2>T &amp; x</h2>a<br>b<p>one <i>two</i>  three<div class="comments"><article>no</article></div></main><aside>s</aside>'
    assert html.main_text(page)[0] == "T & x\na b\none two three"
    assert html.main_text("<p>kept</p><script>var a='</p>';</script><form><p>no</p></form><p>end <b")[0] == "kept\nend"
    assert html.main_text("a < b <3 c<p>x</p></p></i><!-- no --><!x><br/>y")[0] == "a < b <3 c\nx\ny"
    assert html.main_text('<p title="a > b">one</p><p title="never closed>two</p>three')[0] == "one\ntwo\nthree"


def test_template_text_is_dropped(spark):
    def page(i):
        body = "".join(f"<div class=box><p>{'alpha beta gamma delta ' * 4}{i} {k}</p></div>" for k in range(2))
        return f"<html><body><div><p>Site slogan here</p></div>{body}<div><p>All rights kept</p></div></body></html>"

    rows = spark.createDataFrame([(i, f"http://one.example/{i}", page(i)) for i in range(12)], "page_id long, url string, html string")
    for r in html.op7_html(rows).collect():
        assert "slogan" not in r["text"] and "rights" not in r["text"] and r["text"].count("alpha") == 8


def test_copies_and_small_hosts(spark):
    def page(i):
        return f"<html><body><div><p>Site slogan here</p></div><div class=box><p>{'alpha beta gamma delta ' * 4}{i}</p><p>of {i}</p></div><div><p>All rights kept</p></div></body></html>"

    schema = "page_id long, url string, html string"
    small = [(i, f"http://h{i}.example/", page(i)) for i in range(12)]
    for r in html.op7_html(spark.createDataFrame(small, schema)).collect():
        assert "slogan" not in r["text"] and "rights" not in r["text"] and r["text"].count("alpha") == 4
    copies = [(i, f"http://one.example/{i % 3}", page(7)) for i in range(4)] + [(3, "http://one.example/0", page(7))] + [(9, "http://two.example/", page(7))]
    for r in html.op7_html(spark.createDataFrame(copies, schema)).collect():
        assert r["text"].count("alpha") == 4 and "of 7" in r["text"]
    for repeated in (small + small, small + small[:5]):
        tokens = lambda rows: {(*r[:5], tuple(r["chain"] or ()), *r[6:]) for r in html.occurrence(spark.createDataFrame(rows, schema)).collect()}
        assert tokens(repeated) == tokens(small)


PAGES = "page_id long, url string, html string, host string, text int"


def words(rng, n):
    return " ".join(f"{rng.choice('bcdfgh')}{rng.randrange(10**5)}" for _ in range(n))


def test_template_decides_on_marked_pages(spark):
    rng = random.Random(4)
    articles = [f"<h1>{words(rng, 3)}</h1><p>{words(rng, 60)}</p><p>{words(rng, 30)}</p>" for _ in range(12)]
    page = lambda a: f"<html><body><div class=top><p>{'some old words ' * 40}</p></div><article>{a}<p>Share this story</p></article><div>end</div></body></html>"
    rows = [(i, f"http://one.example/{i}", page(a), "clash", 0) for i, a in enumerate(articles)]
    copies = [(100 + i, f"http://two.example/{i}", page(articles[0]).replace("end", f"end {i}"), "clash", 0) for i in range(12)]
    got = {r["page_id"]: r for r in html.op7_html(spark.createDataFrame(rows + copies + [rows[0]], PAGES)).collect()}
    for i, a in enumerate(articles):
        plain = [x.partition("<")[0] for x in a.split(">")]
        assert got[i]["text"] == "\n".join(x for x in plain if x) and got[i]["decided"] == "host"
        assert "Share" in html.main_text(rows[i][2])[0]  # without the template it stays
    # Copies of one article do not make its text a template.
    assert all(got[100 + i]["text"].endswith("Share this story") and got[100 + i]["text"].count("\n") == 3 for i in range(12))


def test_template_finds_the_box_without_marks(spark):
    rng = random.Random(5)
    legal, rows, want = words(rng, 300), [], {}
    for i in range(10):
        title, body = words(rng, 4), [words(rng, rng.randint(5, 80)) for _ in range(rng.randint(2, 5))]
        links = "".join(f"<li><a href=/{k}>{words(rng, 5)}</a></li>" for k in range(40))
        html_i = f"<html><body><div id=x{i}><ul>{links}</ul></div><div class=m><h2>{title}</h2>{''.join(f'<p>{b}</p>' for b in body)}</div><div class=z><p>{legal}</p><p>{words(rng, 3)}</p></div></body></html>"
        rows.append((i, "http://plain.example/", html_i, None, None))
        want[i] = "\n".join([title, *body])
    lone = (50, "http://lone.example/", rows[0][2].replace(want[0].split("\n")[1], "another text of its own " * 5), None, None)
    got = {r["page_id"]: r for r in html.op7_html(spark.createDataFrame([*rows, lone], PAGES)).collect()}
    assert {i: got[i]["text"] for i in want} == want and {got[i]["decided"] for i in want} == {"host"}
    assert got[50]["decided"] == "all" and "another text" in got[50]["text"] and legal not in got[50]["text"]


def brute_template(pages):
    """Template tokens of each host by whole occurrence vectors."""
    hosts, first = defaultdict(dict), {}
    for _, url, h, *_ in pages:
        first[h] = min(first.get(h, "~"), url.split("/")[2])
    for h, host in first.items():
        hosts[host][h] = html.page_tokens(h)
    merged = defaultdict(dict)
    for host, own in hosts.items():
        for at in (host, "*"):
            merged[at].update(own)
    found = set()
    for host, own in merged.items():
        vectors, places = defaultdict(dict), defaultdict(list)
        for h, tokens in own.items():
            for t, x in tokens.items():
                vectors[t][h] = x[4]
                places[t].append(x[6])
        classes = defaultdict(list)
        for t, v in vectors.items():
            classes[frozenset(v.items())].append(t)
        kind = {t: x[0] for tokens in own.values() for t, x in tokens.items()}
        at = {t: sum(x) / len(x) for t, x in places.items()}
        valid = [(c, min(map(at.get, c)), max(map(at.get, c)), len(v)) for v, c in classes.items() if len(c) >= 3 and len(v) >= 3 and any(kind[t] == html.TAG for t in c)]
        if valid:
            _, _, lo, hi = max((n, b - a, a, b) for c, a, b, n in valid)
            found |= {(host, t) for c, a, b, n in valid if a >= lo and b <= hi and 2 * n >= len(own) for t in c}
    return found


def test_classes_equal_whole_vectors(spark):
    given = spark.read.parquet(f"{SF}/pages.parquet").limit(80).collect()
    rng = random.Random(6)
    rows = [(r["page_id"], f"http://h{rng.randrange(7)}.example/x", r["html"], None, None) for r in given]
    rows += [(900 + i, f"http://h{i % 3}.example/y", f"<div><p>{'a b c'[: i % 5]}</p><p>same</p></div>" * (1 + i % 2), None, None) for i in range(12)] + rows[:9]
    got = {(r["host"], r["token"]) for r in html.template_tokens(html.occurrence(spark.createDataFrame(rows, PAGES))).collect()}
    assert got == brute_template(rows) and len(got) > 100


def test_template_needs_no_names(spark):
    import re

    given = [(r["page_id"], r["url"], r["html"], None, None) for r in spark.read.parquet(f"{SF}/pages.parquet").collect()]
    bare = lambda h: re.sub(r"<(/?)(?:article|main|nav|footer|header|aside|form)\b", r"<\1div", h).replace(' class="ad"', "")
    want = {r["page_id"]: r["text"] for r in html.op7_html(spark.createDataFrame(given, PAGES)).collect()}
    got = html.op7_html(spark.createDataFrame([(p, u, bare(h), *x) for p, u, h, *x in given], PAGES)).collect()
    assert {r["page_id"]: r["text"] for r in got} == want and all(r["decided"] != "page" for r in got)
    assert sum(html.main_text(bare(h))[0] != want[p] for p, _, h, *_ in given) > 0.9 * len(given)


def test_broken_pages_take_linear_time():
    import time

    for unit in ("<a ", "<a \"", "</script", "<script></script", "<div class=x>", "<b><p>", "<li>", "<!--", "<", "<p a='\">", "&"):
        page = unit * (300_000 // len(unit))
        began = time.perf_counter()
        html.main_text(page)
        html.page_tokens(page)
        assert time.perf_counter() - began < 6, unit


def test_top_k(spark):
    rng = np.random.default_rng(2)
    rows = [(i, [float(x) for x in rng.normal(0, 1 + i % 3, 6)]) for i in range(300)]
    rows[7] = (7, rows[6][1])
    rows += [(400, None), (401, [1.0, None, 1.0, 1.0, 1.0, 1.0]), (450, [float("nan")] * 6), (402, [float("inf")] + [0.0] * 5)]
    got = topk.op9_top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    v = {i: np.floor(256 * np.array(x)).astype(np.int64) for i, x in rows if x and all(y is not None and np.isfinite(y) for y in x)}
    want = []
    for q in (i for i in v if i % 50 == 0):
        best = sorted((-int(v[q] @ v[c]), c) for c in v if c != q)[:5]
        want += [(q, k + 1, c, -s) for k, (s, c) in enumerate(best)]
    assert sorted(map(tuple, got)) == sorted(want)
    assert topk.op9_top_k(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def brute_top(v, step=50, k=5):
    want = []
    for q in (i for i in v if i % step == 0):
        best = sorted((-int(v[q] @ v[c]), c) for c in v if c != q)[:k]
        want += [(q, r + 1, c, -s) for r, (s, c) in enumerate(best)]
    return sorted(want)


def test_top_k_over_many_bands(spark, monkeypatch):
    for name, value in (("CANDIDATE_GROUP", 64), ("QUERY_BLOCK", 4), ("HEAD", 32)):
        monkeypatch.setattr(topk, name, value)
    rng = np.random.default_rng(5)
    rows = [(i, [float(x) for x in rng.normal(0, 1, 6) * np.exp(rng.normal(0, 1.5)) * (i % 13 > 0)]) for i in range(1200)]
    rows += [(2000, [1.0, 2.0]), (2001, [9.0] * 9), (2050, [])]
    schema = "vec_id long, embedding array<double>, query_id int, rank string, band int, v string"
    frame = spark.createDataFrame([(*r, 1, "x", 2, None) for r in rows], schema)
    v = {i: np.floor(256 * np.array(x)).astype(np.int64) for i, x in rows if len(x) == 6}
    for part in (1, 7):  # whichever row comes first
        got = topk.op9_top_k(frame.orderBy(topk.F.desc("vec_id")).repartition(part)).collect()
        assert sorted(map(tuple, got)) == brute_top(v)
    assert topk.groups_within(np.array([[3.0, 4.0]]), np.array([50.0]), np.array([np.inf, 20.0, 10.0, 9.0]), np.array([2, 5, 6, 9])) == 6
    assert topk.groups_within(np.array([[0.0, 0.0]]), np.array([0.0]), np.array([np.inf, 1.0]), np.array([1, 2])) == 2


def test_top_k_brings_no_vectors_to_the_driver(spark, monkeypatch):
    for name, value in (("CANDIDATE_GROUP", 64), ("QUERY_BLOCK", 4), ("HEAD", 32), ("SETS", 3), ("SET_GROUPS", 8), ("LOT_BLOCKS", 2)):
        monkeypatch.setattr(topk, name, value)
    frame_type, brought = type(spark.range(1)), []
    whole = frame_type.toPandas
    monkeypatch.setattr(frame_type, "toPandas", lambda self: brought.append(self.columns) or whole(self))
    rng = np.random.default_rng(8)
    rows = [(i, [float(x) for x in rng.normal(0, 1, 6) * (200.0 if i % 17 == 0 else 1.0)]) for i in range(1500)]
    v = {i: np.floor(256 * np.array(x)).astype(np.int64) for i, x in rows}
    got = topk.op9_top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    assert sorted(map(tuple, got)) == brute_top(v)
    assert not any("v" in columns for columns in brought)


@pytest.mark.parametrize("size", [30, 9_000, 1_000_000, 200_000_000])
def test_meetings_are_exact_at_any_length(size):
    rng = np.random.default_rng(4)
    c = rng.integers(-size, size, (3000, 12)).astype(float)
    assert (topk.wide(topk.narrow(c), 12) == c).all()
    c = c[np.argsort(-(c * c).sum(1), kind="stable")]
    q, ids = c[::100], np.arange(3000)
    out, _ = topk.best(q, ids[::100], np.full(len(q), -np.inf), c, ids, np.eye(12), 5)
    for i in range(len(q)):
        s = c.astype(np.int64) @ q[i].astype(np.int64)
        order = [j for j in np.lexsort((ids, -s)) if j != ids[::100][i]][:5]
        assert [x[1:] for x in out[5 * i : 5 * i + 5]] == [(j, s[j]) for j in order]


def test_pruning_is_exact_and_saves_work():
    rng = np.random.default_rng(3)
    c = np.floor(rng.normal(0, 1, (5000, 16)) * np.exp(rng.normal(0, 1, (5000, 1))) * 50)
    c = c[np.argsort(-(c * c).sum(1), kind="stable")]
    q, ids = c[::500], np.arange(5000)
    _, basis = np.linalg.eigh(c.T @ c)
    out, finished = topk.best(q, ids[::500], np.full(len(q), -np.inf), c, ids, basis[:, ::-1].copy(), 5)
    for i in range(len(q)):
        s = (c @ q[i]).astype(np.int64)
        order = [j for j in np.lexsort((ids, -s)) if j != ids[::500][i]][:5]
        assert [x[1] for x in out[5 * i : 5 * i + 5]] == order
    assert finished < 0.5 * len(q) * len(c)


def cell(x):
    if x is None or pd.isna(x):
        return ""
    return str(round(float(x), 6)) if isinstance(x, (int, float)) or hasattr(x, "dtype") else str(x)


def plain(df):
    return sorted(tuple(map(cell, r)) for r in df[sorted(df.columns)].itertuples(index=False))


def test_registered_queries_equal_sql(spark):
    con = duckdb.connect()
    for t in ("documents", "pages", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    for name, sql in queries.oracle_sql().items():
        ours, theirs = queries.queries()[name](spark, SF).toPandas(), con.execute(sql).df()
        assert sorted(ours.columns) == sorted(theirs.columns)
        assert plain(ours) == plain(theirs)
