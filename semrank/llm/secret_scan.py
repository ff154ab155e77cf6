"""Secret scans by dictionary-primed zstandard novelty.

Base patterns find assigned credentials, access key ids and long hex runs. Beside them, values that
are assigned in a sensitive context (a name with a word of authentication anywhere in it) are candidates.
Each candidate is compressed with a dictionary primed from the text around it and from the identifiers of the whole text (the
``IDENTIFIERS`` most frequent ones), without the candidate's own other occurrences, so that a secret written twice does not prime itself;
its novelty is the bytes that this adds, less an empty frame, per byte. A random string stays
incompressible under any dictionary, a word or a name from the surroundings does not. Candidates
of a novelty of ``NOVEL`` or more become spans of kind ``novel`` unless a base span overlaps them.

At scale: a narrow projection. Built-in functions tell which texts can hold a span; only those are
handed to Python, whole. No shuffle.

Defined cases: null is empty; texts without a span have the digest of the empty string and empty spans;
repeated rows are scanned row by row; an empty table gives an empty table; extra columns are left unread.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterator

import pandas as pd
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from semrank.llm.text import whole

KINDS = ("assign", "access", "hex", "novel")
#: The base patterns with their least lengths; re.A keeps "either case" to ASCII letters.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
LEAST = {"assign": 6, "access": 20, "hex": 24}
#: Names that make a context sensitive, and the shape of a value.
NAMES = (
    "auth", "bearer", "credential", "passphrase", "passcode", "pwd", "private", "signature", "session", "access", "encryption", "license_key", "client_id",
    "passw", "secret", "token", "key",
)
SENSITIVE = re.compile("|".join(NAMES), re.I | re.A)
#: A whole name and, looked ahead, its value, which may be the next match's name.
CONTEXT = re.compile(r"""([A-Za-z0-9_-]++)(?=["']?\x20*(?:[:=]\x20*|\x20)["']?([A-Za-z0-9+/_=-]{16,}))""", re.A)
IDENTIFIER = re.compile(r"[A-Za-z_][A-Za-z0-9_]{2,}")
AROUND, NOVEL = 2000, 0.55
#: A dictionary's size bounds what compressing one candidate costs.
IDENTIFIERS = 2000


def names_of(text: str) -> Counter:
    return Counter(IDENTIFIER.findall(text))


def dictionary(names: Counter, text: str, value: str) -> str:
    """The most frequent identifiers of a text, less those that stand in occurrences of ``value`` alone."""
    inside = Counter(IDENTIFIER.findall(value))
    times = text.count(value) if inside else 0
    left = ((w, n - times * inside[w]) for w, n in names.items())
    return " ".join(sorted(w for _, w in sorted((-n, w) for w, n in left if n > 0)[:IDENTIFIERS]))


def novelty(text: str, start: int, end: int, names: Counter | None = None) -> float:
    """Marginal compressed bytes per byte of text[start:end], with its surroundings and the text's identifiers as dictionary."""
    value = text[start:end].encode()
    # wider by one value, so that an occurrence across the edge is seen whole
    wide, blank = AROUND + end - start, " " * (end - start)
    before = text[max(0, start - wide) : start].replace(text[start:end], blank)[-AROUND:]
    after = text[end : end + wide].replace(text[start:end], blank)[:AROUND]
    known = dictionary(names_of(text) if names is None else names, text, text[start:end])
    primer = (known + "\n" + after + before).encode("utf-8", "replace")
    if len(primer) < 8:
        primer = primer.ljust(8)
    packer = zstandard.ZstdCompressor(level=19, dict_data=zstandard.ZstdCompressionDict(primer, dict_type=zstandard.DICT_TYPE_RAWCONTENT), write_content_size=False, write_dict_id=False)
    return (len(packer.compress(value)) - len(packer.compress(b""))) / max(1, len(value))


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the patterns' matches that are long enough."""
    out = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST["assign"]]
    out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST["access"]]
    out += [(m.start(), 2, m.end()) for m in HEX.finditer(text) if m.end() - m.start() >= LEAST["hex"]]
    return sorted(out)


def scan(text: str) -> dict:
    base = base_spans(text)
    more, value_of, names = [], {}, None
    for m in CONTEXT.finditer(text):
        s, e = m.span(2)
        if not SENSITIVE.search(m[1]) or any(a < e and s < b for a, _, b in base):
            continue
        if re.search("[0-9]", m[2]) and re.search("[A-Za-z]", m[2]):
            names = names or names_of(text)
            if (x := novelty(text, s, e, names)) >= NOVEL:
                more.append((s, 3, e))
                value_of[s, 3] = x
    names = names or (names_of(text) if base else None)
    for s, k, e in base:
        inner = ASSIGN.match(text, s).span(2) if k == 0 else (s, e)
        value_of[s, k] = novelty(text, *inner, names)
    written = lambda spans: ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)
    every = sorted(base + more)
    return {
        **{f"n_{KINDS[k]}": sum(x[1] == k for x in every) for k in range(4)},
        "base_sha256": hashlib.sha256(written(base).encode()).hexdigest(),
        "spans": written(every),
        "novelty": ",".join(f"{value_of[s, k]:.3f}" for s, k, _ in every),
    }


def may_hold(text: str | Column) -> Column:
    """False only for texts that have no span of any kind."""
    t, low = whole(text), F.lower(whole(text))
    out = t.contains("AKIA") | t.rlike("[0-9a-f]{24}")
    for word in NAMES:
        out = out | low.contains(word)
    return out


RETURNS = T.StructType([T.StructField(n, T.LongType()) for n in ("n_assign", "n_access", "n_hex", "n_novel")] + [T.StructField(n, T.StringType()) for n in ("base_sha256", "spans", "novelty")])


@F.pandas_udf(RETURNS)
def scanned(texts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
    nothing = scan("")
    for s in texts:
        yield pd.DataFrame([nothing if t is None else scan(t) for t in s], columns=list(nothing))


def secret_scan(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, counts by kind, the digest of base spans, all spans and their novelty."""
    d = docs.select(F.col(doc_id).alias("doc_id"), scanned(F.when(may_hold(text), whole(text))).alias("s"))
    return d.select("doc_id", "s.*")
