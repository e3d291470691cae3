"""Secret scan: keyword automaton first, anchored expressions near its hits, then embedded checksums.

An Aho-Corasick automaton walks the lower-cased text once; each kind's expression is tried only where one of its keywords
starts, so texts without keywords cost one walk.  Runs of hex digits have no keyword and are found by their own expression.
Tokens that carry a checksum (prefix, 30 base-62 characters, then the CRC-32 of those in six base-62 characters) are
reported as kind `checked` only if it holds.

Kinds `assign`, `access` and `hex` follow a fixed contract: matches are leftmost and don't overlap within a kind, and
those below the least length are dropped after they have consumed their text.

Defined cases: null and empty texts have no spans; positions are code points with exclusive ends; repeated rows each get
their row; extra columns are kept by redact() and ignored by scan().
"""

from __future__ import annotations

import hashlib
import re
import zlib

import ahocorasick
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ratiobin.llm.common import table

# Fixed values of the contract: keywords, expressions and least lengths of the base kinds.
ASSIGN_WORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ASSIGN_LEAST = 6
ACCESS_WORD = "akia"
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
ACCESS_LEAST = 20
HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "checked")
# Prefixes of published token formats that end in a base-62 CRC-32.
CHECKED_WORDS = ("ghp_", "gho_", "ghu_", "ghs_", "ghr_", "npm_")
CHECKED = re.compile(r"(?:gh[pousr]|npm)_([0-9A-Za-z]{30})([0-9A-Za-z]{6})(?![0-9A-Za-z])")
BASE62 = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"

_LOWER = {c: c + 32 for c in range(65, 91)}
_automaton = None


def automaton() -> ahocorasick.Automaton:
    global _automaton
    if _automaton is None:
        built = ahocorasick.Automaton()
        for word in (*ASSIGN_WORDS, ACCESS_WORD, *CHECKED_WORDS):
            kind = "assign" if word in ASSIGN_WORDS else "access" if word == ACCESS_WORD else "checked"
            built.add_word(word, (kind, len(word)))
        built.make_automaton()
        _automaton = built
    return _automaton


def checksum62(body: str) -> str:
    """CRC-32 of the body in six base-62 characters."""
    rest, out = zlib.crc32(body.encode()), ""
    for _ in range(6):
        rest, digit = divmod(rest, 62)
        out = BASE62[digit] + out
    return out


def find_spans(text: str | None) -> list[tuple[str, int, int]]:
    """(kind, start, end) by start, then kind as listed."""
    if not text:
        return []
    lowered = text.lower()
    if len(lowered) != len(text):
        lowered = text.translate(_LOWER)
    starts: dict[str, list[int]] = {"assign": [], "access": [], "checked": []}
    for end, (kind, size) in automaton().iter(lowered):
        starts[kind].append(end - size + 1)
    spans = []
    for kind, expression in (("assign", ASSIGN), ("access", ACCESS), ("checked", CHECKED)):
        free = 0
        for at in sorted(starts[kind]):
            if at >= free and (m := expression.match(text, at)):
                free = m.end()
                good = len(m[2]) >= ASSIGN_LEAST if kind == "assign" else len(m[0]) >= ACCESS_LEAST if kind == "access" else checksum62(m[1]) == m[2]
                if good:
                    spans.append((kind, at, m.end()))
    spans += [("hex", *m.span()) for m in HEX.finditer(text)]
    return sorted(spans, key=lambda s: (s[1], KINDS.index(s[0])))


def joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{kind}:{a}:{b}" for kind, a, b in spans)


def scan(docs: DataFrame) -> DataFrame:
    """(doc_id, text) to counts of base kinds, digest of base spans, and all spans."""

    def run(frames):
        for frame in frames:
            found = [find_spans(t) for t in frame["text"]]
            base = [[s for s in spans if s[0] != "checked"] for spans in found]
            yield pd.DataFrame({
                "doc_id": frame["doc_id"],
                **{f"n_{kind}": [sum(s[0] == kind for s in spans) for spans in base] for kind in KINDS[:3]},
                "base_sha256": [hashlib.sha256(joined(spans).encode()).hexdigest() for spans in base],
                "spans": [joined(spans) for spans in found],
                "n_checked": [len(spans) - len(b) for spans, b in zip(found, base, strict=True)],
            })

    return docs.select("doc_id", "text").mapInPandas(run, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_checked long")


def blanked(text: str | None, mark: str) -> str | None:
    if not text:
        return text
    out, at = [], 0
    for _, a, b in find_spans(text):
        if b > at:
            if a >= at:
                out += [text[at:a], mark]
            at = b
    return "".join([*out, text[at:]]) if at else text


def redact(docs: DataFrame, mark: str = "[SECRET]") -> DataFrame:
    """docs with every secret span replaced in `text` by a mark; all other columns stay."""

    @F.pandas_udf("string")
    def clean(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: blanked(t, mark), na_action="ignore")

    return docs.withColumn("text", clean("text"))


def op7_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))
