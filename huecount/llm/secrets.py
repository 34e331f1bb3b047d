"""Secret scans: fixed patterns, and literals that source or configuration text assigns to sensitive names.

The patterns find ``assign`` (a sensitive word, an assignment sign, a long value), ``access`` (access key
ids) and ``hex`` (long hexadecimal runs). The lexer reads statements of common source and configuration
syntax (``name = "value"``, ``"name": 'value'``, ``name: value``, ``export NAME=value``, ``name := value``,
``name => value``, ``<name>value</name>``), keeps a table of constants per text, follows names that are
assigned from other names or joined from constants with ``+`` or adjacent literals, and scores each
literal by the name it ends up under: sensitive words in the name, minus words that say the value is
public, plus the literal's length, mixed character classes and entropy, minus placeholders. Values of
several words are scored as their characters without blanks, private keys in PEM form count as secret. All
literals that a high enough value is joined from are spans of kind ``literal``.

Defined results: a null text is empty and has no spans; ids, repeats and extra columns do not matter;
long texts are scanned whole; an empty table gives an empty result. Offsets are code points, end
exclusive.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from huecount.llm.common import slices

KINDS = ("assign", "access", "hex", "literal")
# Fixed patterns and lengths of the base scan.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
HEX = re.compile(r"[0-9a-f]{16,}")
ASSIGN_VALUE = 12
_ASSIGN_WORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")

Span = tuple[int, int, str]


def base_spans(text: str) -> list[Span]:
    """A run of the access or hex alphabet matches from its first possible start to its end, so asking for
    its least length in the pattern finds the same runs as dropping short ones afterwards; an assignment
    has to be matched first and dropped then, since a dropped one still uses up its characters."""
    low = text.lower()
    found = []
    if any(w in low for w in _ASSIGN_WORDS):
        found = [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= ASSIGN_VALUE]
    found += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text)]
    return found + [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]


# What names say about their values. Fixed values.
SENSITIVE = {"password": 4, "passwd": 4, "pwd": 4, "passphrase": 4, "secret": 4, "token": 3, "credential": 4, "credentials": 4,
             "apikey": 4, "accesskey": 4, "privatekey": 4, "auth": 2, "bearer": 3, "key": 2, "api": 1, "access": 1, "private": 1,
             "signing": 2, "encryption": 2, "salt": 2, "session": 1, "cookie": 1, "client": 1, "webhook": 1, "dsn": 2, "pin": 1}
PUBLIC = {"public": 4, "id": 1, "name": 3, "url": 2, "path": 3, "file": 3, "length": 4, "count": 4, "type": 4, "expiry": 4, "ttl": 4,
          "label": 3, "hint": 3, "policy": 3, "placeholder": 5, "example": 3, "test": 1, "max": 3, "min": 3, "limit": 3, "column": 3}
FAKE = re.compile(r"(?i)^(?:x+|\*+|\.+|-+|<.*>|\$\{.*\}|\{\{.*\}\}|%\w+%|changeme|change_me|your[-_ ].*|example.*|placeholder.*|null|none|true|false|undefined|todo|redacted.*|\[.*\])$")
REPORT_FROM = 5.0
_PEM = re.compile(r"\s*-----BEGIN ")
_MESSAGE = re.compile(r"(?i)\b(?:please|enter|your|must|invalid|required|forgot|forgotten|incorrect|cannot)\b")

# Every repeat is possessive: a text is lexed in time proportional to its length, and no string, name or list of parts has a limit.
_NAME = r"[A-Za-z_$][A-Za-z0-9_$.\-]*+"
_STRING = r'"(?:[^"\\\n]|\\.)*+"' + r"|'(?:[^'\\\n]|\\.)*+'" + r"|`(?:[^`\\\n]|\\.)*+`"
# A key over several lines: bare, in a block of a configuration file, or in quotes that may span lines.
_BLOCK = r"-----BEGIN [A-Z0-9 ]*+-----[ \t\r]*+\n[^-]*+(?:-(?!----(?:BEGIN|END) )[^-]*+)*+-----END [A-Z0-9 ]*+-----"
_PART = rf"""(?P<plus>[ \t]*+(?:\+[ \t]*+)?)(?P<part>{_STRING}|(?<=[+ ]){_NAME}(?![A-Za-z0-9_(]))(?![ \t]*+[:=])"""
_STATEMENT = re.compile(
    rf"""(?:["'](?P<quoted>{_NAME})["']|(?P<bare>(?<![A-Za-z0-9_$.\-]){_NAME}))(?P<index>\[\s*+["']{_NAME}["']\s*+\])?"""
    rf"""[ \t]*+(?P<sign>:=|=>|==?(?!=)|:(?![:/]))[ \t]*+(?:(?:[|>][+-]?|["'`]{{1,3}}+)?\s*+(?P<block>{_BLOCK})["'`]{{0,3}}+|(?P<value>{_STRING}|[^\s"'`,;(){{}}\[\]<>]++))"""
    rf"""(?P<more>(?:{re.sub(r"\?P<\w+>", "?:", _PART)})*+)""",
)
_ELEMENT = re.compile(rf"<(?P<name>{_NAME})>(?P<value>[^<>]++)</(?P=name)>")
_PIECE = re.compile(_PART)
_PARTS = re.compile(r"[A-Z]+(?![a-z])|[A-Z]?[a-z]+|\d+")


def name_score(name: str) -> int:
    words = [w.lower() for w in _PARTS.findall(name)]
    joined = ["".join(p) for p in zip(words, words[1:], strict=False)]
    best = sum(sorted((SENSITIVE.get(w, 0) for w in {*words, *joined}), reverse=True)[:2])
    return best - max([PUBLIC.get(w, 0) for w in words], default=0)


def literal_score(value: str) -> float:
    """From -9 (no secret) to about 4. Of several words the blanks do not count; a message to a reader loses."""
    if _PEM.match(value):
        return 4.0 if " PRIVATE KEY" in value else -9.0
    solid = "".join(value.split())
    words = len(value.split())
    if len(solid) < 8 or FAKE.match(value) or len(set(solid)) < 4:
        return -9.0
    n, counts = len(solid), Counter(solid)
    entropy = -sum(c / n * math.log2(c / n) for c in counts.values())
    classes = sum(bool(re.search(p, value if words <= 2 else solid)) for p in (r"[a-z]", r"[A-Z]", r"\d", r"[^A-Za-z0-9]"))
    if classes == 1 and value.isalpha():
        return -2.0
    several = (0.5 + 3.0 * bool(_MESSAGE.search(value))) * (words > 2)
    return 0.5 * classes + min(entropy, 4.0) / 2 - 1.0 + (n >= 16) * 0.5 - several


def _unquoted(piece: str) -> str | None:
    return re.sub(r"\\(.)", r"\1", piece[1:-1], flags=re.S) if piece[:1] in "\"'`" and len(piece) > 1 else None


def name_literal_pairs(text: str) -> list[tuple[str, str, tuple[tuple[int, int], ...]]]:
    """(name, constant value, places) of every assignment whose value is known. The places are those of all
    literals that the value is joined from, where they are written; a name assigned from a known name
    gives that name's places again."""
    known: dict[str, tuple[str, tuple[tuple[int, int], ...]]] = {}
    pairs = []

    def resolve(piece: str, at: int) -> tuple[str, tuple[tuple[int, int], ...]] | None:
        if (plain := _unquoted(piece)) is not None:
            return plain, ((at + 1, at + len(piece) - 1),)
        return known.get(piece) or known.get(piece.rpartition(".")[2])

    for m in sorted([*_STATEMENT.finditer(text), *_ELEMENT.finditer(text)], key=lambda m: m.start()):
        if m.re is _ELEMENT:
            pairs.append((m["name"], m["value"], (m.span("value"),)))
            continue
        if m["sign"] == "==":
            continue
        name = (m["quoted"] or m["bare"]) + re.sub(r"[^\w$.\-]", "", "." + m["index"] if m["index"] else "")
        unknown = ("", ()) if m["more"].lstrip().startswith("+") else (m["value"], (m.span("value"),))
        value, places = (m["block"], (m.span("block"),)) if m["block"] else resolve(m["value"], m.start("value")) or unknown
        if m["more"]:
            values, seen = [value], dict.fromkeys(places)
            for p in _PIECE.finditer(text, m.start("more"), m.end("more")):
                got = resolve(p["part"], p.start("part"))
                if got is not None:
                    values.append(got[0])
                    seen.update(dict.fromkeys(got[1]))
                elif "+" not in p["plus"]:
                    break
            # Only names that are joined to themselves can pass the text's length; their places are all kept.
            value, places = "".join(values)[: len(text)], tuple(seen)
        known[name.rpartition(".")[2]] = known[name] = (value, places)
        pairs.append((name, value, places))
    return pairs


def literal_spans(text: str) -> list[Span]:
    """Spans of literals that end up under sensitive names."""
    if "=" not in text and ":" not in text and "</" not in text:  # no statement is without
        return []
    found = {}
    for name, value, places in name_literal_pairs(text):
        score = name_score(name)
        if score >= 2 and score + literal_score(value) >= REPORT_FROM:
            found.update({(a, b): (a, b, "literal") for a, b in places if b > a})
    return list(found.values())


def scan(text: str | None) -> list[Span]:
    """All spans by start, then kind."""
    text = text or ""
    return sorted(base_spans(text) + literal_spans(text), key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


def joined(spans: list[Span]) -> str:
    return ",".join(f"{kind}:{a}:{b}" for a, b, kind in spans)


def redact(text: str, spans: list[Span], mark: str = "[secret]") -> str:
    """The text with every span, overlapping ones together, replaced by a mark. Of an assignment the name
    stays: only its value goes."""
    out, at = [], 0
    for a, b, kind in spans:
        if kind == "assign":
            a = ASSIGN.match(text, a).start(2)
        if b <= at:
            continue
        if a >= at:
            out += [text[at:a], mark]
        at = b
    return "".join([*out, text[at:]])


def op10_secret_scan(docs: DataFrame) -> DataFrame:
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in slices(batches):
            rows = []
            for doc, text in zip(batch["doc_id"], batch["text"], strict=True):
                spans = scan(text)
                n = Counter(s[2] for s in spans)
                base = joined([s for s in spans if s[2] != "literal"])
                rows.append((doc, n["assign"], n["access"], n["hex"], hashlib.sha256(base.encode()).hexdigest(), joined(spans), n["literal"]))
            yield pd.DataFrame(rows, columns=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_literal"])

    light = docs.select(F.col("doc_id").cast("string").alias("doc_id"), "text")
    out = light.mapInPandas(run, "doc_id string, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_literal long")
    return out.withColumn("doc_id", F.col("doc_id").cast("long"))


def redacted(docs: DataFrame) -> DataFrame:
    """docs with secrets replaced in their texts; n_chars follows. No document goes."""
    @F.pandas_udf("string")
    def clean(text: pd.Series) -> pd.Series:
        return pd.Series([t if t is None or not (s := scan(t)) else redact(t, s) for t in text], dtype=object)

    out = docs.withColumn("text", clean("text"))
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out
