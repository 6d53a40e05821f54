"""Secret scans: a keyword automaton finds where to look, anchored patterns decide what is there, and
kinds with an embedded checksum or structure count only if it holds.

Offsets are code points, ends exclusive. Kinds and their order are fixed; the first three are plain
patterns (``assign``, ``access``, ``hex``), the others are validated.
"""

from __future__ import annotations

import base64
import binascii
import json
import re
import zlib
from bisect import bisect_left
from functools import cache

import ahocorasick
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from assetmill.llm.batches import SLICE, map_rows, raw_text

KINDS = ("assign", "access", "hex", "github", "npm", "jwt", "pem")

# The words and forms that the scan is defined by.
WORDS = ("password", "passwd", "secret", "token", "api_key", "apikey")
GITHUB_PREFIXES = ("ghp_", "gho_", "ghu_", "ghs_", "ghr_")
BASE62 = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"
LEAST_ASSIGNED, LEAST_ACCESS, LEAST_HEX = 6, 20, 24


def _either_case(words: str) -> str:
    return re.sub(r"[a-z]", lambda m: f"[{m[0].upper()}{m[0]}]", words)


ASSIGN = re.compile((_either_case("(?:password|passwd|secret|token|api_?key)") + r"""["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""").encode())
ACCESS = re.compile(rb"AKIA[A-Z0-9]+")
HEX = re.compile(rb"[0-9a-f]+")
CHECKED = re.compile(rb"(?:gh[pousr]_|npm_)([A-Za-z0-9]{30})([A-Za-z0-9]{6})(?![A-Za-z0-9])")
TOKEN_RUN = re.compile(rb"[A-Za-z0-9_-]*")
PEM_HEAD = re.compile(rb"-----BEGIN ((?:[A-Z0-9]+ )*PRIVATE KEY)-----")
PEM_END = re.compile(rb"(?=-----END ((?:[A-Z0-9]+ )*PRIVATE KEY)-----)")
PEM_BODY = re.compile(rb"[A-Za-z0-9+/=\s:,-]*")
#: Hex digits become one letter, so that a run of enough of them is a fixed keyword.
_HEX_CLASS = bytes(0x68 if chr(i) in "0123456789abcdef" else 0x20 for i in range(256))
_HEX_RUN = b"h" * LEAST_HEX


def checksum62(body: bytes) -> str:
    """CRC32 in six digits of base 62."""
    n, out = zlib.crc32(body), ""
    for _ in range(6):
        n, d = divmod(n, 62)
        out = BASE62[d] + out
    return out


@cache
def keyword_automaton() -> ahocorasick.Automaton:
    """Lower-case keywords over bytes read as Latin-1; each leads to (length, kind)."""
    a = ahocorasick.Automaton()
    for w in WORDS:
        a.add_word(w, (len(w), "assign"))
    a.add_word("akia", (4, "access"))
    for w in GITHUB_PREFIXES:
        a.add_word(w, (len(w), "github"))
    a.add_word("npm_", (4, "npm"))
    a.add_word("eyj", (3, "jwt"))
    a.add_word("-----begin ", (11, "pem"))
    a.make_automaton()
    return a


def _is_jwt(head: bytes) -> bool:
    try:
        return "alg" in json.loads(base64.urlsafe_b64decode(head + b"=" * (-len(head) % 4)))
    except (ValueError, binascii.Error, TypeError):
        return False


class _Reader:
    """One text. What a hit finds out about the run of characters that it stands in serves all hits of that run,
    so that no text costs more than its length."""

    def __init__(self, buf: bytes):
        self.buf = buf
        self.token = (0, 0, None)  # run of token characters: start, end, end of the whole token if there is one
        self.body = (0, 0)  # run of characters that a key block may hold
        self.ends: dict[bytes, list[int]] | None = None

    def jwt(self, at: int) -> tuple[int, bool] | None:
        buf, run = self.buf, lambda i: TOKEN_RUN.match(buf, i).end()
        if not buf.startswith(b"eyJ", at):
            return None
        if not self.token[0] <= at < self.token[1]:
            head, end = run(at), None
            if buf.startswith(b".eyJ", head):
                body = run(head + 4)
                if body > head + 4 and buf.startswith(b".", body) and run(body + 1) > body + 1:
                    end = run(body + 1)
            self.token = (at, head, end)
        _, head, end = self.token
        return (end, _is_jwt(buf[at:head])) if end and head > at + 3 else None

    def pem(self, at: int) -> tuple[int, bool] | None:
        m = PEM_HEAD.match(self.buf, at)
        if not m:
            return None
        if self.ends is None:
            self.ends = {}
            for e in PEM_END.finditer(self.buf):
                self.ends.setdefault(e[1], []).append(e.start())
        if not self.body[0] <= m.end() < self.body[1]:
            self.body = (m.end(), PEM_BODY.match(self.buf, m.end()).end())
        places = self.ends.get(m[1], [])
        k = bisect_left(places, m.end())
        if k == len(places) or places[k] > self.body[1]:
            return None
        return places[k] + len(b"-----END -----") + len(m[1]), True

    def look(self, at: int, kind: str) -> tuple[int, bool] | None:
        """End of the match of ``kind`` that starts exactly here, and whether it counts."""
        buf = self.buf
        if kind == "assign":
            m = ASSIGN.match(buf, at)
            return m and (m.end(), len(m[1]) >= LEAST_ASSIGNED)
        if kind == "access":
            m = ACCESS.match(buf, at)
            return m and (m.end(), len(m[0]) >= LEAST_ACCESS)
        if kind in ("github", "npm"):
            m = CHECKED.match(buf, at)
            return m and (m.end(), checksum62(m[1]) == m[2].decode())
        return self.jwt(at) if kind == "jwt" else self.pem(at)


def byte_spans(buf: bytes) -> list[tuple[int, int, str]]:
    """(start, end, kind) in bytes, by start and then kind. Of each kind leftmost first, without overlap;
    a match that fails its own test still uses up its characters."""
    found, past = [], dict.fromkeys(KINDS, 0)
    hits = sorted((end + 1 - n, kind) for end, (n, kind) in keyword_automaton().iter(buf.lower().decode("latin-1")))
    reader = _Reader(buf)
    for at, kind in hits:
        if at >= past[kind] and (m := reader.look(at, kind)):
            past[kind] = m[0]
            if m[1]:
                found.append((at, m[0], kind))
    shape = buf.translate(_HEX_CLASS)
    at = shape.find(_HEX_RUN)
    while at >= 0:
        end = HEX.match(buf, at).end()
        found.append((at, end, "hex"))
        at = shape.find(_HEX_RUN, end)
    return sorted(found, key=lambda x: (x[0], KINDS.index(x[2])))


def spans(buf: bytes) -> list[tuple[int, int, str]]:
    """``byte_spans`` in code points."""
    found = byte_spans(buf)
    if not found or buf.isascii():
        return found
    marks, count, done = {}, 0, 0
    for at in sorted({x for s in found for x in s[:2]}):
        count, done = count + len(buf[done:at].decode("utf-8", "replace")), at
        marks[at] = count
    return [(marks[a], marks[b], k) for a, b, k in found]


def joined(found: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in found)


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base (text of the plain spans), spans (text of all spans).

    Null and empty texts have no spans; every row is scanned on its own and whole, so equal rows give
    equal results and an empty table gives none. Other columns are not read.
    """

    def make():
        def one(doc_id, buf):
            found = spans(buf)
            base = [s for s in found if s[2] in KINDS[:3]]
            return doc_id, *(sum(s[2] == k for s in base) for k in KINDS[:3]), joined(base), joined(found)

        return one

    return map_rows(docs.select("doc_id", raw_text()), make, "doc_id long, n_assign long, n_access long, n_hex long, base string, spans string")


def redact(docs: DataFrame, mark: str = "[{kind}]") -> DataFrame:
    """The same rows and columns with each span replaced by its kind's mark, overlaps by one; null texts
    stay null. ``n_chars``, if there, follows the text."""

    def make():
        def one(buf):
            if buf is None:
                return (None,)
            out, past = [], 0
            for a, b, kind in byte_spans(buf):
                if a >= past:
                    out += [buf[past:a], mark.format(kind=kind).encode()]
                    past = b
                elif b > past:
                    past = b
            return (b"".join([*out, buf[past:]]).decode("utf-8", "replace"),)

        return one

    rest = [c for c in docs.columns if c != "text"]
    text_at = docs.columns.index("text")
    out = with_rows(docs, make)
    if "n_chars" in rest:
        out = out.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.char_length("text").cast(docs.schema["n_chars"].dataType)))
    return out.select(*docs.columns) if text_at >= 0 else out


def with_rows(docs: DataFrame, make) -> DataFrame:
    """``docs`` with its text replaced in place, row by row, by an Arrow function."""
    import pyarrow as pa

    from assetmill.plans.ship import ship

    ship(docs.sparkSession)
    schema, at = docs.schema, docs.columns.index("text")

    def run(batches):
        one = make()
        for whole in batches:
            for first in range(0, whole.num_rows, SLICE):
                batch = whole.slice(first, SLICE)
                texts = [one(v.as_buffer().to_pybytes() if v.is_valid else None)[0] for v in batch.column(at)]
                columns = list(batch.columns)
                columns[at] = pa.array(texts, batch.schema.field(at).type)
                yield pa.record_batch(columns, schema=batch.schema)

    return docs.mapInArrow(run, schema)
