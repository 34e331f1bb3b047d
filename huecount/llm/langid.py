"""Language identification by a bidirectional gated recurrent network over bytes.

Two gated recurrent layers read the bytes of a window in both directions; a softmax on their joined
states labels every position. A document's probabilities are the mean of its positions' log
probabilities, renormalised. The network is trained in numpy by backpropagation through time with Adam
on windows drawn from a bounded sample of labelled documents. Prediction covers whole texts: a text is
cut into windows of WINDOW bytes, and windows of a whole Arrow batch run side by side, so memory and
time per byte do not depend on lengths. Input bytes enter through a table of 256 rows (weights times
one-hot byte), so a step is one lookup and one small product.

The sample: documents are ranked by a hash of doc_id and each contributes one window from a place that a
second hash chooses; SAMPLE_PER_LANGUAGE documents of each language at most, of the MAX_LANGUAGES most frequent
languages. It is the only part that does not cover all rows, and only fitting reads it. A language beyond these is
never predicted.

Defined results: a null text, or one without a letter, is ``und`` with score 0; without any labelled
document everything is ``und``; one language gets everything; repeated rows predict alike; an empty
table gives an empty result; lang, source and doc_id never enter a prediction; extra columns are ignored.
"""

from __future__ import annotations

import re

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from huecount.llm.common import slices

HIDDEN = 8
WINDOW = 96
TRAIN_WINDOW = 64
SAMPLE_PER_LANGUAGE = 600
MAX_LANGUAGES = 256
STEPS, BATCH, RATE = 160, 256, 0.02
UNKNOWN = "und"
_MAY_BE_LETTER = re.compile(r"[^\W\d_]")
GATES = 3  # update, reset, candidate


def has_letter(text: str | None) -> bool:
    """Whether a character of the text is a letter (general category L). The pattern also lets through
    fractions and numerals, which are none."""
    return any(m[0].isalpha() for m in _MAY_BE_LETTER.finditer(text or ""))


def held_out() -> Column:
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2


def _sigmoid(x: np.ndarray) -> np.ndarray:
    """Logistic function through tanh, which does not overflow."""
    return np.float32(0.5) * np.tanh(np.float32(0.5) * x) + np.float32(0.5)


class ByteGru:
    """Bidirectional gated recurrent network. Parameters of a direction: table (256, 3H) with biases folded
    in, recurrent weights for update and reset (H, 2H), for the candidate (H, H); then the output layer."""

    def __init__(self, languages: list[str], hidden: int = HIDDEN, seed: int = 7):
        rng = np.random.default_rng(seed)
        h, self.languages = hidden, list(languages)
        self.p: dict[str, np.ndarray] = {}
        for d in "fb":
            self.p[f"{d}E"] = rng.normal(0, 0.3, (256, GATES * h)).astype(np.float32)
            self.p[f"{d}U"] = rng.normal(0, 1 / np.sqrt(h), (h, 2 * h)).astype(np.float32)
            self.p[f"{d}C"] = rng.normal(0, 1 / np.sqrt(h), (h, h)).astype(np.float32)
        self.p["W"] = rng.normal(0, 1 / np.sqrt(2 * h), (2 * h, len(languages))).astype(np.float32)
        self.p["o"] = np.zeros(len(languages), np.float32)
        self.hidden = h

    def _layer(self, d: str, x: np.ndarray):
        """States (T, B, H) of direction d over bytes x (T, B), and what backpropagation needs."""
        h, (steps, batch) = self.hidden, x.shape
        table, recur, cand = self.p[f"{d}E"], self.p[f"{d}U"], self.p[f"{d}C"]
        states, saved = np.empty((steps, batch, h), np.float32), []
        s = np.zeros((batch, h), np.float32)
        for t in range(steps) if d == "f" else range(steps - 1, -1, -1):
            e = table[x[t]]
            gate = _sigmoid(e[:, : 2 * h] + s @ recur)
            z, r = gate[:, :h], gate[:, h:]
            rs = r * s
            c = np.tanh(e[:, 2 * h :] + rs @ cand)
            saved.append((t, s, z, r, rs, c))
            s = states[t] = z * s + (1 - z) * c
        return states, saved

    def _states(self, d: str, x: np.ndarray, live: np.ndarray | None) -> np.ndarray:
        """As _layer, for prediction only: each gate apart, so that every array is contiguous, and all
        nonlinear functions by exp."""
        h, (steps, batch) = self.hidden, x.shape
        table, recur, cand = self.p[f"{d}E"], self.p[f"{d}U"], self.p[f"{d}C"]
        parts = [np.ascontiguousarray(-table[:, :h]), np.ascontiguousarray(-table[:, h : 2 * h]), np.ascontiguousarray(-2 * table[:, 2 * h :])]
        uz, ur, uc = np.ascontiguousarray(-recur[:, :h]), np.ascontiguousarray(-recur[:, h:]), -2 * cand
        states = np.empty((steps, batch, h), np.float32)
        s, (z, r, c) = np.zeros((batch, h), np.float32), np.empty((3, batch, h), np.float32)
        with np.errstate(over="ignore"):
            for t in range(steps) if d == "f" else range(steps - 1, -1, -1):
                for gate, part, u in ((z, parts[0], uz), (r, parts[1], ur)):
                    np.matmul(s, u, out=gate)
                    gate += part.take(x[t], axis=0)
                    np.exp(gate, out=gate)
                    gate += 1
                    np.reciprocal(gate, out=gate)
                r *= s
                np.matmul(r, uc, out=c)
                c += parts[2].take(x[t], axis=0)
                np.exp(c, out=c)
                c += 1
                np.reciprocal(c, out=c)
                c += c
                c -= 1
                if live is not None:
                    z[~live[t]] = 1
                new = states[t]
                np.subtract(s, c, out=new)
                new *= z
                new += c
                s = new
        return states

    def positions(self, x: np.ndarray, live: np.ndarray | None = None) -> np.ndarray:
        """Log probabilities (languages, T, B) of every position."""
        f, b = self._states("f", x, live), self._states("b", x, live)
        h, (steps, batch) = self.hidden, x.shape
        out = self.p["W"][:h].T @ f.reshape(-1, h).T + self.p["W"][h:].T @ b.reshape(-1, h).T + self.p["o"][:, None]
        out -= out.max(axis=0)
        out -= np.log(np.exp(out).sum(axis=0))
        return out.reshape(-1, steps, batch)

    def gradients(self, x: np.ndarray, y: np.ndarray):
        """Mean cross entropy over all positions of full windows, and its gradients."""
        h, (steps, batch) = self.hidden, x.shape
        layers = {d: self._layer(d, x) for d in "fb"}
        joined = np.concatenate([layers["f"][0], layers["b"][0]], axis=2)
        out = joined @ self.p["W"] + self.p["o"]
        out -= out.max(axis=2, keepdims=True)
        prob = np.exp(out)
        prob /= prob.sum(axis=2, keepdims=True)
        rows = np.arange(batch)
        loss = -np.log(prob[:, rows, y] + 1e-9).mean()
        d_out = prob
        d_out[:, rows, y] -= 1
        d_out /= steps * batch
        g = {k: np.zeros_like(v) for k, v in self.p.items()}
        g["W"], g["o"] = np.tensordot(joined, d_out, ([0, 1], [0, 1])), d_out.sum(axis=(0, 1))
        d_joined = d_out @ self.p["W"].T
        for d, part in (("f", d_joined[:, :, :h]), ("b", d_joined[:, :, h:])):
            ds = np.zeros((batch, h), np.float32)
            inputs, at = np.empty((steps, batch, GATES * h), np.float32), []
            for t, s, z, r, rs, c in reversed(layers[d][1]):
                ds = ds + part[t]
                dc = ds * (1 - z) * (1 - c * c)
                drs = dc @ self.p[f"{d}C"].T
                dz, dr = ds * (s - c) * z * (1 - z), drs * s * r * (1 - r)
                gate = np.concatenate([dz, dr], axis=1)
                g[f"{d}C"] += rs.T @ dc
                g[f"{d}U"] += s.T @ gate
                ds = ds * z + drs * r + gate @ self.p[f"{d}U"].T
                inputs[len(at), :, : 2 * h], inputs[len(at), :, 2 * h :] = gate, dc
                at.append(t)
            flat = x[at].ravel()
            order = np.argsort(flat, kind="stable")
            seen, first = np.unique(flat[order], return_index=True)
            g[f"{d}E"][seen] = np.add.reduceat(inputs.reshape(-1, GATES * h)[order], first, axis=0)
        return loss, g

    def fit(self, windows: np.ndarray, labels: np.ndarray, steps: int = STEPS, batch: int = BATCH, rate: float = RATE, seed: int = 11):
        """Adam on random batches, languages drawn evenly. windows: (N, T) bytes."""
        rng = np.random.default_rng(seed)
        of = [np.flatnonzero(labels == k) for k in range(len(self.languages))]
        m, v = ({k: np.zeros_like(x) for k, x in self.p.items()} for _ in range(2))
        for n in range(1, steps + 1):
            pick = np.array([rng.choice(of[k]) for k in rng.integers(0, len(of), batch)])
            _, g = self.gradients(np.ascontiguousarray(windows[pick].T), labels[pick])
            size = np.sqrt(sum(float((x * x).sum()) for x in g.values()))
            lr = rate * min(1.0, 2 * (1 - (n - 1) / steps))
            for k in self.p:
                x = g[k] * min(1.0, 1.0 / (size + 1e-9))
                m[k] = 0.9 * m[k] + 0.1 * x
                v[k] = 0.99 * v[k] + 0.01 * x * x
                self.p[k] = (self.p[k] - lr * (m[k] / (1 - 0.9**n)) / (np.sqrt(v[k] / (1 - 0.99**n)) + 1e-6)).astype(np.float32)
        return self

    def documents(self, texts: list[bytes], window: int = WINDOW, side_by_side: int = 2048) -> np.ndarray:
        """Probabilities (documents, languages): positions of all windows, pooled."""
        total = np.zeros((len(texts), len(self.languages)))
        n = np.array([len(t) for t in texts], np.int64)
        per_doc = -(-n // window)
        owner = np.repeat(np.arange(len(texts)), per_doc)
        nth = np.arange(len(owner)) - np.repeat(np.cumsum(per_doc) - per_doc, per_doc)
        data = np.frombuffer(b"".join(texts) + bytes(window), np.uint8)
        start = np.repeat(np.cumsum(n) - n, per_doc) + nth * window
        length = np.minimum(window, np.repeat(n, per_doc) - nth * window)
        order = np.argsort(-length, kind="stable")  # full windows together, without masks
        for i in range(0, len(order), side_by_side):
            part = order[i : i + side_by_side]
            longest = int(length[part].max())
            steps = np.arange(longest)[:, None]
            live = steps < length[part][None, :]
            whole = bool(live.all())
            logp = self.positions(data[start[part][None, :] + steps], None if whole else live)
            pooled = (logp if whole else logp * live).sum(axis=1)
            np.add.at(total, owner[part], pooled.T)
        mean = total / np.maximum(n, 1)[:, None]
        prob = np.exp(mean - mean.max(axis=1, keepdims=True)) if len(texts) else total
        return prob / prob.sum(axis=1, keepdims=True) if len(texts) else prob


def training_windows(docs: DataFrame, usable: Column, window: int = TRAIN_WINDOW, per_language: int = SAMPLE_PER_LANGUAGE) -> pd.DataFrame:
    """lang and bytes of the bounded sample. Languages' numbers come from all rows; a hash threshold per
    language then lets through about as many documents as wanted."""
    labelled = docs.where(usable & F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("text").rlike(r"\p{L}"))
    light = docs.where(usable & F.col("lang").isNotNull())
    numbers = light.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(MAX_LANGUAGES).collect()
    if not numbers:
        return pd.DataFrame({"lang": [], "window": []})
    share = docs.sparkSession.createDataFrame([(r[0], min(1.0, 1.25 * per_language / r[1])) for r in numbers], "s_lang string, share double")
    place = lambda seed: F.pmod(F.xxhash64("doc_id", F.lit(seed)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    chars = F.length("text")
    first = (F.floor(place(2) * F.greatest(chars - window, F.lit(0))) + 1).cast("int")
    picked = labelled.join(F.broadcast(share), F.col("lang") == F.col("s_lang")).where(place(1) < F.col("share"))  # MAX_LANGUAGES rows
    rows = picked.select("lang", "doc_id", F.substring("text", first, F.lit(window)).alias("window")).toPandas()
    rows = rows.sort_values(["lang", "doc_id", "window"], ignore_index=True)
    return rows.groupby("lang", group_keys=False).head(per_language)


def fitted(docs: DataFrame, usable: Column, seed: int = 7, **options) -> ByteGru | None:
    sample = training_windows(docs, usable)
    if not len(sample):
        return None
    languages = sorted(sample["lang"].unique())
    # Short texts repeat until the window is full.
    rows = [((w.encode("utf-8", "surrogatepass") + b" ") * TRAIN_WINDOW)[:TRAIN_WINDOW] for w in sample["window"]]
    x = np.frombuffer(b"".join(rows), np.uint8).reshape(len(rows), TRAIN_WINDOW)
    y = sample["lang"].map({k: i for i, k in enumerate(languages)}).to_numpy(np.int64)
    return ByteGru(languages, seed=seed).fit(x, y, **options) if len(languages) > 1 else ByteGru(languages, seed=seed)


def labeller(model: ByteGru | None):
    """A vectorised function of texts: (lang_pred, score)."""

    def labels(texts: list[str | None]) -> pd.DataFrame:
        pred, score = [UNKNOWN] * len(texts), [0.0] * len(texts)
        at = [i for i, t in enumerate(texts) if model is not None and has_letter(t)]
        if at:
            prob = model.documents([texts[i].encode("utf-8", "surrogatepass") for i in at])
            for i, row in zip(at, prob, strict=True):
                k = int(row.argmax())
                pred[i], score[i] = model.languages[k], float(row[k])
        return pd.DataFrame({"lang_pred": pred, "score": score})

    @F.pandas_udf("lang_pred string, score double")
    def label(text: pd.Series) -> pd.DataFrame:
        parts = [labels(part["text"].tolist()) for part in slices([text.to_frame("text")])]
        return pd.concat(parts, ignore_index=True) if parts else labels([])

    return label


def predicted(docs: DataFrame, model: ByteGru | None) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every document."""
    rows = docs.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), labeller(model)("text").alias("label"))
    return rows.select("doc_id", "held_out", "label.lang_pred", "label.score")


def language_id(docs: DataFrame) -> DataFrame:
    return predicted(docs, fitted(docs, ~held_out()))


def identified(docs: DataFrame, least: float = 0.3) -> DataFrame:
    """docs without those whose language is unknown or whose score is under ``least``."""
    known = docs.withColumn("__label", labeller(fitted(docs, ~held_out()))("text"))
    return known.where((F.col("__label.lang_pred") != UNKNOWN) & (F.col("__label.score") >= least)).drop("__label")


def op1_language_id(docs: DataFrame) -> DataFrame:
    return language_id(docs)
