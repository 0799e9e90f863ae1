"""Secret scan with multipart credential linking.

Strong parts (key assignments, access identifiers, long hexadecimal strings) are reported wherever they
stand. Weak parts (a bare string that could be a secret, a user or client name, an endpoint) are
reported only where the parts that complete them stand in the same scope: a secret needs an identifier, an identifier
a secret, an endpoint both. The scope of a part is its paragraph and the ones next to it (an empty line ends a paragraph), within `REACH` code
points of the part. No part has a greatest length: a run of characters is taken whole, and redaction leaves no end of it.

All parts lie in one document, so the interval join is a search in the sorted starts of the other kinds, next to
the text; no pairs are made, nothing is shuffled, and the work grows with the text.

Defined results: a null text is empty and has no spans; places are code points, ends exclusive; case of the
key words is folded for ASCII only; a column with the name of the output is replaced; repeated rows are each judged.
"""

from __future__ import annotations

import re
from bisect import bisect_left, bisect_right

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hamcover.llm.batchwise import with_struct

#: Order of kinds that start at one place: fixed values.
KINDS = ("assign", "access", "hex", "secret", "ident", "endpoint")

#: Fixed patterns.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
MIN_ASSIGN, MIN_ACCESS, MIN_HEX = 6, 20, 24
_KEYS = ("passw", "secret", "token", "apikey", "api_key")

SECRET = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_-]{20,}=*(?![A-Za-z0-9+/_=-])")
IDENT = re.compile(r"""(?<![a-z0-9])(?:client_?id|user_?name|user|login|account_?id|key_?id)["']?\x20*[:=]\x20*["']?[A-Za-z0-9@_.-]{3,}""", re.I | re.A)
_NAMES = ("client", "user", "login", "account", "key")
ENDPOINT = re.compile(r"[A-Za-z][A-Za-z0-9+.-]{1,20}://[^\s\"'<>]{3,}|arn:[a-z0-9-]+:[A-Za-z0-9:/_-]{3,}", re.A)
_EMPTY_LINE = re.compile(r"\n[\x20\t\r]*\n")

#: Code points between parts of one credential.
REACH = 1_000

SPANS = "array<struct<kind:string,start:int,end:int>>"

_HEX_BYTES = bytes(120 if chr(i) in "0123456789abcdef" else 32 for i in range(256))
_LONG_BYTES = bytes(120 if chr(i).isascii() and (chr(i).isalnum() or chr(i) in "+/_-") else 32 for i in range(256))


def _looks_random(x: str) -> bool:
    return any(c.islower() for c in x) and any(c.isupper() for c in x) and any(c.isdigit() for c in x)


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """The strong parts, by start, then kind. The tests on the whole text are cheap and never lose a match."""
    found = []
    low = text.lower()
    if any(k in low for k in _KEYS):
        found += [("assign", m.start(), m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= MIN_ASSIGN]
    if "AKIA" in text:
        found += [("access", m.start(), m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= MIN_ACCESS]
    if b"x" * MIN_HEX in text.encode("utf-8", "surrogatepass").translate(_HEX_BYTES):
        found += [("hex", m.start(), m.end()) for m in HEX.finditer(text) if m.end() - m.start() >= MIN_HEX]
    return sorted(found, key=lambda x: (x[1], KINDS.index(x[0])))


def weak_spans(text: str) -> list[tuple[str, int, int]]:
    """Parts that count only beside others."""
    found = []
    if b"x" * 20 in text.encode("utf-8", "surrogatepass").translate(_LONG_BYTES):
        found += [("secret", m.start(), m.end()) for m in SECRET.finditer(text) if _looks_random(m[0])]
    low = text.lower()
    if any(k in low for k in _NAMES) and ("=" in text or ":" in text):
        found += [("ident", m.start(), m.end()) for m in IDENT.finditer(text)]
    if "://" in text or "arn:" in text:
        found += [("endpoint", m.start(), m.end()) for m in ENDPOINT.finditer(text)]
    return found


class _Near:
    """Intervals of one role, of which the one nearest to a place is asked for."""

    def __init__(self, spans: list[tuple[str, int, int]]):
        spans = sorted((s, e) for _, s, e in spans)
        self.starts, self.ends, top = [s for s, _ in spans], [], 0
        for _, e in spans:
            self.ends.append(top := max(top, e))

    def meets(self, lo: int, hi: int) -> bool:
        """True if an interval has a place in [lo, hi)."""
        k = bisect_left(self.starts, hi)
        return k > 0 and self.ends[k - 1] > lo


def linked_spans(text: str, base: list[tuple[str, int, int]], reach: int = REACH) -> list[tuple[str, int, int]]:
    """The weak parts whose complements stand in their scope, outside of strong parts."""
    weak = weak_spans(text)
    if not weak:
        return []
    strong = _Near(base)
    weak = [x for x in weak if not strong.meets(x[1], x[2])]
    roles = {"secret": _Near([x for x in [*base, *weak] if x[0] in ("assign", "hex", "secret")]), "ident": _Near([x for x in [*base, *weak] if x[0] in ("access", "ident")])}
    cuts = [m.start() for m in _EMPTY_LINE.finditer(text)]
    out = []
    for kind, s, e in weak:
        k = bisect_right(cuts, s)
        lo = max(s - reach, cuts[k - 2] + 1 if k > 1 else 0)
        k = bisect_left(cuts, e) + 1
        hi = min(e + reach, cuts[k] if k < len(cuts) else len(text))
        needs = [r for r in roles if r != kind]
        if all(roles[r].meets(lo, hi) for r in needs):
            out.append((kind, s, e))
    return out


def scan(text: str | None, reach: int = REACH) -> tuple[list, list]:
    text = text or ""
    base = base_spans(text)
    both = sorted({*base, *linked_spans(text, base, reach)}, key=lambda x: (x[1], KINDS.index(x[0])))
    return base, both


def _make():
    as_dicts = lambda spans: [{"kind": k, "start": s, "end": e} for k, s, e in spans]
    return lambda texts: [tuple(map(as_dicts, scan(t))) for t in texts]


def scan_secrets(docs: DataFrame, text: str = "text", output: str = "secrets") -> DataFrame:
    """All columns of docs and a struct: base spans, and spans with the linked ones."""
    return with_struct(docs, text, output, f"struct<base:{SPANS},spans:{SPANS}>", _make)


def _redact(text: str | None) -> str | None:
    if not text:
        return text
    spans, out, at = scan(text)[1], [], 0
    for kind, s, e in spans:
        if s >= at:
            out += [text[at:s], f"<{kind}>"]
        at = max(at, e)
    return "".join([*out, text[at:]]) if spans else text


def redacted(docs: DataFrame) -> DataFrame:
    """The documents with every reported span replaced by its kind in angle brackets; n_chars follows where it was right before."""
    mark = "__redacted"
    made = with_struct(docs, "text", mark, "struct<text:string>", lambda: lambda texts: [(_redact(t),) for t in texts])
    new = {"text": F.col(f"{mark}.text")}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col("n_chars") == F.length("text"), F.length(F.col(f"{mark}.text"))).otherwise(F.col("n_chars")).cast(docs.schema["n_chars"].dataType)
    return made.withColumns(new).select(*docs.columns)


def listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")


def op4_secret_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    found = scan_secrets(docs)
    base = F.col("secrets.base")
    n = lambda kind: F.size(F.filter(base, lambda x: x["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return found.select("doc_id", n("assign"), n("access"), n("hex"), F.sha2(listed(base), 256).alias("base_sha256"), listed(F.col("secrets.spans")).alias("spans"))


QUERIES = {"op4_secret_links": op4_secret_links}
ORACLES: dict[str, str] = {}
