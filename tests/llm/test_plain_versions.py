"""Verdicts and probabilities computed once more, number by number."""

import math
import random
from collections import defaultdict

import numpy as np
import pytest

from huecount.llm import langid, quality
from tests.llm.test_documents import brute_counts


def plain_thresholds(rows):
    """Fences per (language, source) from sorted lists of bucket middles. rows: (lang, source, counts)."""
    names, groups = quality.COUNTS, defaultdict(lambda: defaultdict(list))
    for lang, source, counts in rows:
        c = dict(zip(names, counts, strict=True))
        for m, (a, b, *_) in quality.MEASURES.items():
            x = c[a] / c[b]
            middle = 0.0 if x <= 0 else 2 * quality.GAMMA ** math.ceil(round(math.log(x) / math.log(quality.GAMMA), 9)) / (quality.GAMMA + 1)
            for level in ((0, lang, source), (1, lang, None), (2, None, None)):
                groups[level][m].append(middle)

    def fences(lang, source):
        level = next(g for g in ((0, lang, source), (1, lang, None), (2, None, None)) if g[0] == 2 or len(groups[g]["symbols"]) >= quality.SMALLEST)
        out = {}
        for m, (_, _, up, down) in quality.MEASURES.items():
            x = sorted(groups[level][m])
            low, q1, q3, high = (x[max(1, math.ceil(q * len(x))) - 1] for q in (1 - quality.TAIL, 0.25, 0.75, quality.TAIL))
            spread = lambda at, q1=q1, q3=q3: quality.FENCE * max(q3 - q1, quality.LEAST_SPREAD * at)
            hi = max(q3 + spread(q3), (1 + 2 * quality.ERROR) * high) if up else math.inf
            lo = min(q1 - spread(q1), (1 - 2 * quality.ERROR) * low) if down else -math.inf
            out[m] = (lo, hi)
        return out

    return fences


def test_verdicts_equal_a_plain_version(spark):
    rng, docs = random.Random(21), []
    for i in range(700):
        lang, source = rng.choice([("en", "a"), ("en", "a"), ("en", "b"), ("de", "b"), (None, "c"), ("fr", None)])
        words = [("w" * rng.randint(2, 9)) + str(rng.randrange(10**4)) for _ in range(rng.choice([3, 30, 80]))]
        if rng.random() < 0.1:
            words[rng.randrange(len(words))] = "#" * rng.randint(1, 60)
        if rng.random() < 0.1:
            words += words[:6]
        sep = "\n" if rng.random() < 0.2 else " "
        docs.append((i, sep.join(words) + ("\nsame line\nsame line" if rng.random() < 0.1 else ""), lang, source))
    docs += [docs[0]] * 3 + [(9000, None, "en", "a"), (9001, " \n ", None, None)]
    frame = spark.createDataFrame(docs, "doc_id long, text string, lang string, source string")
    got = sorted((r["doc_id"], r["base_failed"], r["kept"]) for r in quality.op5_quality(frame).collect())
    counted = [(d, lang, source, brute_counts(t)) for d, t, lang, source in docs]
    failed = lambda c: c[0] < 10 or 100 * c[4] > 20 * c[0]
    fences, want = plain_thresholds([(lang, source, c) for _, lang, source, c in counted if not failed(c)]), []
    for d, lang, source, c in counted:
        kept = not failed(c)
        if kept:
            named = dict(zip(quality.COUNTS, c, strict=True))
            for m, (lo, hi) in fences(lang, source).items():
                a, b = quality.MEASURES[m][:2]
                kept = kept and lo <= named[a] / named[b] <= hi
        want.append((d, failed(c), kept))
    assert got == sorted(want) and 0 < sum(not f and not k for _, f, k in want) < 200


def plain_probabilities(model, text, window):
    """Mean log probability of the positions, state by state."""
    sig = lambda x: 1 / (1 + np.exp(-x))
    h, total = model.hidden, np.zeros(len(model.languages))
    for at in range(0, len(text), window):
        part, states = text[at : at + window], {}
        for d, order in (("f", range(len(part))), ("b", range(len(part) - 1, -1, -1))):
            e, u, c = (model.p[d + x].astype(np.float64) for x in "EUC")
            s = np.zeros(h)
            for t in order:
                x = e[part[t]]
                z, r = sig(x[:h] + s @ u[:, :h]), sig(x[h : 2 * h] + s @ u[:, h:])
                s = z * s + (1 - z) * np.tanh(x[2 * h :] + (r * s) @ c)
                states[d, t] = s
        for t in range(len(part)):
            logits = np.concatenate([states["f", t], states["b", t]]) @ model.p["W"] + model.p["o"]
            total += logits - np.log(np.exp(logits - logits.max()).sum()) - logits.max()
    mean = total / len(text)
    p = np.exp(mean - mean.max())
    return p / p.sum()


def test_probabilities_equal_a_plain_version():
    model = langid.ByteGru(["de", "en", "fr"], seed=3)
    model.p["o"] = np.array([0.3, -0.1, 0.2], np.float32)
    texts = [b"a", b"Some words of a text, " * 3, bytes(range(256)), b"x" * 96, b"yz" * 97]
    got = model.documents(texts, window=96, side_by_side=3)
    for t, p in zip(texts, got, strict=True):
        assert p == pytest.approx(plain_probabilities(model, t, 96), abs=2e-5)
    assert model.documents(texts, window=7) == pytest.approx(np.array([plain_probabilities(model, t, 7) for t in texts]), abs=2e-5)
