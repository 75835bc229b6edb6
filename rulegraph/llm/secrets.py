"""Secret scans: keyword automaton, anchored expressions near its hits, embedded checksums.

One pass of an Aho-Corasick automaton over the text (A-Z lower-cased) finds keyword
hits; the regular expressions are tried only there, anchored. Long hexadecimal runs
have no keyword: a character-class scan finds them. Kinds with a checksum or a
structure of their own are kept only if it holds.
"""

from __future__ import annotations

import base64
import hashlib
import json
import re
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import tidied
from .word_ids import text_lists

_OUT = pa.schema([("doc_id", pa.int64()), ("n_assign", pa.int64()), ("n_access", pa.int64()), ("n_hex", pa.int64()), ("base_sha256", pa.string()), ("spans", pa.string())])

#: Kinds in the order of the contract; the first three are the base.
KINDS = ("assign", "access", "hex", "checked", "jwt", "pem")

_KEY = "(?:[pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])"
ASSIGN = re.compile(_KEY + r"""["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")
CHECKED = re.compile(r"(?:gh[pousr]_|npm_)([0-9A-Za-z]{30})([0-9A-Za-z]{6})(?![0-9A-Za-z])")
JWT = re.compile(r"(eyJ[A-Za-z0-9_-]+)\.(eyJ[A-Za-z0-9_-]+)\.[A-Za-z0-9_-]+")
PEM = re.compile(r"-----BEGIN ([A-Z ]*PRIVATE KEY)-----[A-Za-z0-9+/=\s]+-----END \1-----")
_DIGITS = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"

#: Keyword (in lower case) to the kind whose expression is tried where it begins.
KEYWORDS = {"password": "assign", "passwd": "assign", "secret": "assign", "token": "assign", "apikey": "assign", "api_key": "assign", "akia": "access", "ghp_": "checked", "gho_": "checked", "ghu_": "checked", "ghs_": "checked", "ghr_": "checked", "npm_": "checked", "eyj": "jwt", "-----begin ": "pem"}
_TRY = {"assign": ASSIGN, "access": ACCESS, "checked": CHECKED, "jwt": JWT, "pem": PEM}


def checksum_62(body: str) -> str:
    """The last six characters that a token with this body must have: its CRC-32 in base 62."""
    n, out = zlib.crc32(body.encode()), ""
    while n:
        n, k = divmod(n, 62)
        out = _DIGITS[k] + out
    return out.rjust(6, "0")


def _is_json(part: str) -> bool:
    try:
        return isinstance(json.loads(base64.urlsafe_b64decode(part + "=" * (-len(part) % 4))), dict)
    except ValueError:
        return False


def _holds(kind: str, m: re.Match) -> bool:
    if kind == "assign":
        return m.end(1) - m.start(1) >= 12
    if kind == "access":
        return m.end() - m.start() >= 18
    if kind == "checked":
        return checksum_62(m[1]) == m[2]
    if kind == "jwt":
        return _is_json(m[1])
    return True


_AUTOMATON = None


def _automaton():
    global _AUTOMATON
    if _AUTOMATON is None:
        import ahocorasick

        _AUTOMATON = ahocorasick.Automaton()
        for word, kind in KEYWORDS.items():
            _AUTOMATON.add_word(word, (len(word), kind))
        _AUTOMATON.make_automaton()
    return _AUTOMATON


def find(text: str | None) -> list[tuple[str, int, int]]:
    """Secrets of a text as (kind, start, end) in code points, by start, then kind in the order of KINDS.

    Within a kind matches are leftmost and do not overlap; a match that fails its
    length or checksum still takes its place, as it would in one pass of the
    expression over the whole text. Null is the empty text.
    """
    if not text:
        return []
    spans = [("hex", m.start(), m.end()) for m in HEX.finditer(text)]
    low = text.encode("utf-8", "surrogatepass").lower().decode("latin-1")  # one character a byte
    ascii_only = len(low) == len(text)
    if not ascii_only:
        raw = text.encode("utf-8", "surrogatepass")
        done, at = 0, 0
    over: dict[str, int] = {}
    for end, (length, kind) in sorted(_automaton().iter(low), key=lambda x: x[0] - x[1][0]):
        start = end - length + 1
        if not ascii_only:
            at += len(raw[done:start].decode("utf-8", "surrogatepass"))
            done = start
            start = at
        if start < over.get(kind, 0) or not (m := _TRY[kind].match(text, start)):
            continue
        over[kind] = m.end()
        if _holds(kind, m):
            spans.append((kind, m.start(), m.end()))
    return sorted(spans, key=lambda x: (x[1], KINDS.index(x[0])))


def _joined(spans) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def redact(text: str | None, mask: str = "[{kind}]") -> str | None:
    """The text with every secret replaced; overlapping spans are merged under the first one's kind."""
    if not text:
        return text
    out, at = [], 0
    for kind, a, b in find(text):
        if a >= at:
            out += [text[at:a], mask.format(kind=kind)]
        at = max(at, b)
    return "".join([*out, text[at:]])


def scan_secrets(docs: DataFrame) -> DataFrame:
    """Secrets of documents (doc_id, text): one row for each input row.

    Returns doc_id, n_assign, n_access, n_hex, base_sha256, spans. A null or empty text
    has none; repeated rows are scanned each; an empty table gives no rows.
    """

    def scan(batches):
        for batch in batches:
            for first, texts in text_lists(batch):
                rows = []
                for text in texts:
                    spans = find(text)
                    base = [x for x in spans if x[0] in KINDS[:3]]
                    counts = [sum(x[0] == k for x in base) for k in KINDS[:3]]
                    rows.append((*counts, hashlib.sha256(_joined(base).encode()).hexdigest(), _joined(spans)))
                columns = [pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), list(_OUT)[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(first, len(texts)), *columns], schema=_OUT)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(tidied(scan), "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")


def redact_column(docs: DataFrame, column: str = "text") -> DataFrame:
    """The same rows and columns with secrets in ``column`` masked by their kind."""

    def mask(batches):
        for batch in batches:
            at = batch.schema.get_field_index(column)
            yield batch.set_column(at, column, pa.array([redact(x.as_py()) for x in batch.column(at)], pa.string()))

    return docs.mapInArrow(tidied(mask), docs.schema)
