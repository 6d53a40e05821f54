"""Removal of repeated byte strings, decided by suffix arrays built through Lyndon groups.

A byte goes if a string of 100 bytes covers it that also starts earlier: in a document with a smaller
id, or earlier in the same one.

Every 100-byte string picks one of its 16-byte grams, its *anchor*: the one with the least hash, the
leftmost of equals. The pick depends on the string alone, so all copies of a string have the same
anchor at the same offset, and the strings of a corpus fall into classes by anchor. What follows only
looks inside classes:

1. Each document is cut into segments, the bytes of a run of strings with one anchor. Equal segments of
   a class (by a cryptographic digest of their bytes) keep their first occurrence; all others go whole. Each
   batch of documents does this on its own before anything is shuffled, so that what a third of all documents
   share is sent once a batch.
2. Classes with several different segments get their bytes. Segments are trimmed to what another
   segment of the class can share with them on both sides of the anchor, and equal pieces merge.
3. The pieces left form a text whose suffix array is built by groups; neighbours that agree in 100 bytes
   are one string, and all but its first occurrence go.

A class with more segments than one suffix array should cover is cut into finer ones, which another step treats
in the same way: first by a second anchor of each string beside its own, then, where that is not enough, by the
whole string. Equal strings stay together at every level, and bytes decide at every level.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from assetmill.llm.batches import arrow_schema, raw_text, tidy
from assetmill.plans.scratch import Scratch
from assetmill.plans.ship import ship

LENGTH, GRAM = 100, 16
WINDOW = LENGTH - GRAM + 1
#: Different segments that one suffix array covers; classes with more are cut into finer ones.
CLASS_ROWS = 512
#: Bytes of a document that are anchored in one piece; positions inside it take 24 bits.
PIECE = 1 << 23
_LOW = np.uint64(0xFFFFFF)
#: Different strings that a task holds before it passes them on.
HELD_STRINGS = 50_000
# Odd numbers that mix a gram's halves, for the first and the second anchor of a string.
_MIX = ((np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)), (np.uint64(0x9FB21C651E98DF25), np.uint64(0xD6E8FEB86659FD93)))


# --- suffix array -------------------------------------------------------------------------------


def suffix_array(text: list[int]) -> list[int]:
    """Suffixes of ``text`` in order, by grouping on their longest Lyndon prefix.

    Groups start as first letters and are visited from the highest down. The suffixes of a visited group
    look for the nearest suffix in front of them in a lower group, over pointers that earlier groups have
    left; runs of one group count how often its word repeats. The suffixes so found now have a longer
    common prefix than the rest of their group, the longer the run the higher, and move into groups of
    their own above it. In the end all suffixes of a group begin with the same Lyndon word and what
    follows it decides, a suffix that is smaller; so one pass in ascending order places the rest.
    """
    n = len(text)
    order = sorted(range(n), key=text.__getitem__)
    place, start, size = [0] * n, [0] * n, [0] * n
    first = 0
    for at, s in enumerate(order):
        place[s] = at
        if text[s] != text[order[first]]:
            first = at
        start[s] = first
        size[first] += 1
    prev, runs = [-1] * n, [0] * n
    end = n
    while end:
        begin = start[order[end - 1]]
        longest: dict[int, int] = {}
        members = order[begin:end]
        if len(members) > 1:
            members.sort()
        for s in members:
            p = s - 1
            while p >= 0 and start[p] > begin:
                p = prev[p]
            if p >= 0 and start[p] == begin:
                count, p = runs[p] + 1, prev[p]
            else:
                count = 1
            runs[s], prev[s] = count, p
            if p >= 0:
                longest[p] = count  # members come in ascending order, so the last is the longest
        if longest:
            by_run: dict[int, list[int]] = {}
            for p, count in longest.items():
                by_run.setdefault(count, []).append(p)
            for count in sorted(by_run, reverse=True):
                moved: dict[int, list[int]] = {}
                for p in by_run[count]:
                    g = start[p]
                    last = g + size[g] - 1
                    at, other = place[p], order[last]
                    order[at], order[last] = other, p
                    place[other], place[p] = at, last
                    size[g] -= 1
                    moved.setdefault(g, []).append(p)
                for g, members in moved.items():
                    new = g + size[g]
                    if new != g:
                        for p in members:
                            start[p] = new
                    size[new] = len(members)
        end = begin
    out, done, free = [-1] * n, [False] * n, list(range(n + 1))
    at, now = -1, n
    while True:
        j = now - 1
        while j >= 0 and not done[j]:
            done[j] = True
            g = start[j]
            out[free[g]] = j
            free[g] += 1
            j = prev[j]
        at += 1
        if at == n:
            return out
        now = out[at]


# --- anchors ------------------------------------------------------------------------------------


def anchors(buf: bytes, level: int = 0, without: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hash and place of each anchor, and the first and last start of the strings that pick it. ``without`` is a
    place that none may pick."""
    b = np.frombuffer(buf, np.uint8).astype(np.uint64)
    two = b[:-1] | b[1:] << np.uint64(8)
    four = two[:-2] | two[2:] << np.uint64(16)
    eight = four[:-4] | four[4:] << np.uint64(32)
    h = eight[:-8] * _MIX[level][0] ^ eight[8:] * _MIX[level][1]
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    least, width = (h & ~_LOW) | np.arange(len(h), dtype=np.uint64), 1
    if without is not None:
        least[without] |= ~_LOW
    while width * 2 <= WINDOW:
        least, width = np.minimum(least[:-width], least[width:]), width * 2
    rest = WINDOW - width
    if rest:
        least = np.minimum(least[:-rest], least[rest:])
    at = (least & _LOW).astype(np.int64)
    first = np.flatnonzero(np.append(True, at[1:] != at[:-1]))
    return h[at[first]], at[first], first, np.append(first[1:], len(at)) - 1


def pack(at, lo, hi):
    """Anchor place, how far before it the first string starts, and how many strings follow that one."""
    return at << 16 | (at - lo) << 8 | (hi - lo)


def unpack(pos):
    at = pos >> 16
    lo = at - (pos >> 8 & 255)
    return at, lo, lo + (pos & 255)


#: Kinds of rows: a mark (strings that go), a segment, a single string.
MARK, SEGMENT, STRING = 1, 2, 3
_FOUND = "kind int, key long, high long, low long, ord long, pos long"
#: A mark has its first start in pos and its last in last; a segment and a string have their bytes.
_STEP = "kind int, key long, ord long, pos long, last long, bytes binary"


def _batch(ddl: str, *columns):
    import pyarrow as pa

    schema = arrow_schema(ddl)
    return pa.record_batch([pa.array(c, f.type) for c, f in zip(columns, schema)], schema=schema)


def _digests(view: memoryview, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """128 bits of each segment, as two columns."""
    from hashlib import blake2b

    raw = b"".join([blake2b(view[a:b], digest_size=16).digest() for a, b in zip(lo.tolist(), (hi + LENGTH).tolist())])
    return np.frombuffer(raw, dtype=np.int64).reshape(-1, 2)


def _cut(batches, piece: int):
    """Rows (ord, text): segments that are first in their batch, and marks for the rest."""
    for batch in batches:
        hs, ds, os_, ps = [], [], [], []
        for ord_, buf in zip(batch.column(0).to_pylist(), batch.column(1)):
            buf = buf.as_py()
            for base in range(0, max(1, len(buf) - LENGTH + 1), piece):
                part = buf[base : base + piece + LENGTH - 1]
                if len(part) < LENGTH:
                    continue
                h, at, lo, hi = anchors(part)
                hs.append(h)
                ds.append(_digests(memoryview(part), lo, hi))
                os_.append(np.full(len(h), ord_, dtype=np.int64))
                ps.append(pack(at + base, lo + base, hi + base))
        if not hs:
            continue
        h, d, o, p = (np.concatenate(x) for x in (hs, ds, os_, ps))
        by = np.lexsort((p, o, d[:, 1], d[:, 0], h))
        h, d, o, p = h[by], d[by], o[by], p[by]
        first = np.append(True, (h[1:] != h[:-1]) | (d[1:] != d[:-1]).any(axis=1))
        # marks travel on keys of their own, spread evenly
        key = np.where(first, h, (o.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)))
        yield _batch(_FOUND, np.where(first, SEGMENT, MARK).astype(np.int32), key.view(np.int64), d[:, 0], d[:, 1], o, p)


def _classes(batches):
    """Rows sorted by key, digest, ord, pos: marks, and the different segments of classes with several."""
    held, tied = None, False

    def rows(keep, kind, h, o, p):
        n = int(keep.sum())
        if n:
            yield _batch("kind int, key long, ord long, pos long", np.full(n, kind, dtype=np.int32), h[keep], o[keep], p[keep])

    for batch in batches:
        kind, *columns = (c.to_numpy() for c in batch.columns)
        marked = kind == MARK
        h, high, low, o, p = columns
        yield from rows(marked, MARK, h, o, p)
        h, high, low, o, p = (c[~marked] for c in columns)
        if held is not None:
            h, high, low, o, p = (np.append(x, y) for x, y in zip(held, (h, high, low, o, p)))
        if not len(h):
            continue
        again = np.append(False, (h[1:] == h[:-1]) & (high[1:] == high[:-1]) & (low[1:] == low[:-1]))
        yield from rows(again, MARK, h, o, p)
        h, high, low, o, p = (c[~again] for c in (h, high, low, o, p))
        same = h[1:] == h[:-1]
        keep = np.append(tied, same) | np.append(same, False)
        tied = bool(np.append(tied, same)[-1])
        keep[-1] = False
        yield from rows(keep, SEGMENT, h, o, p)
        held = tuple(c[-1:] for c in (h, high, low, o, p))
    if held is not None and tied:
        yield from rows(np.ones(1, dtype=bool), SEGMENT, held[0], held[3], held[4])


def _fetch(batches):
    """Rows (ord, text, wanted): the bytes of segments."""
    for batch in batches:
        out: list[tuple] = []
        for ord_, buf, wanted in zip(*batch.columns):
            o, buf = ord_.as_py(), buf.as_py()
            for w in wanted.as_py():
                _, lo, hi = unpack(w["pos"])
                out.append((SEGMENT, w["key"], o, w["pos"], 0, buf[lo : hi + LENGTH]))
            if len(out) > 20_000:
                yield _batch(_STEP, *zip(*out))
                out = []
        if out:
            yield _batch(_STEP, *zip(*out))


# --- one class ----------------------------------------------------------------------------------


def _common(a: bytes, b: bytes) -> int:
    """Length of the common prefix."""
    low, high = 0, min(len(a), len(b))
    if a[:high] == b[:high]:
        return high
    while low < high:
        mid = (low + high + 1) // 2
        if a[:mid] == b[:mid]:
            low = mid
        else:
            high = mid - 1
    return low


def _shared(parts: list[bytes]) -> list[int]:
    """For each string the longest prefix that it shares with any other."""
    by, out = sorted(range(len(parts)), key=parts.__getitem__), [0] * len(parts)
    for x, y in zip(by, by[1:]):
        n = _common(parts[x], parts[y])
        out[x], out[y] = max(out[x], n), max(out[y], n)
    return out


def class_marks(segments: list[tuple[int, int, bytes]]) -> list[tuple[int, int, int]]:
    """Of the segments (ord, pos, bytes) of one class: (ord, first, last) start of runs of strings that also
    start earlier."""
    sides = []
    for ord_, pos, seg in segments:
        at, lo, hi = unpack(pos)
        sides.append((seg[: at - lo][::-1], seg[at - lo :], at - lo, at - hi))
    right, left = _shared([s[1] for s in sides]), _shared([s[0] for s in sides])
    pieces: dict[tuple[bytes, int], list[tuple[int, int]]] = {}
    for (ord_, pos, seg), (_, _, far, near), r, l in zip(segments, sides, right, left):
        far, near = min(l, far), max(LENGTH - r, near)
        if near <= far:
            at, lo, _ = unpack(pos)
            pieces.setdefault((seg[at - lo - far : at - lo + LENGTH - near], far), []).append((ord_, at - far))
    marks: list[tuple[int, int, int]] = []
    distinct = []
    for (piece, _), holders in pieces.items():
        holders.sort()
        last = len(piece) - LENGTH
        marks += [(o, s, s + last) for o, s in holders[1:]]
        distinct.append((piece, *holders[0]))
    if len(distinct) > 1:
        text: list[int] = []
        owner: list[tuple[int, int]] = []
        for k, (piece, _, _) in enumerate(distinct):
            text += [c + 1 for c in piece]
            text.append(0)
            owner += [(k, i) for i in range(len(piece) + 1)]
        again: list[list[int]] = [[] for _ in distinct]
        held, same = None, []

        def settle():
            if len(same) > 1:
                best = min(same, key=lambda x: (distinct[x[0]][1], distinct[x[0]][2] + x[1]))
                for x in same:
                    if x is not best:
                        again[x[0]].append(x[1])

        for s in suffix_array(text):
            k, i = owner[s]
            piece = distinct[k][0]
            if i + LENGTH > len(piece):
                continue
            string = piece[i : i + LENGTH]
            if string == held:
                same.append((k, i))
            else:
                settle()
                held, same = string, [(k, i)]
        settle()
        for (_, o, s), starts in zip(distinct, again):
            starts.sort()
            for i, x in enumerate(starts):
                if i and starts[i - 1] == x - 1:
                    marks[-1] = (o, marks[-1][1], s + x)
                else:
                    marks.append((o, s + x, s + x))
    return marks


def finer(key: int, pos: int, seg: bytes) -> list[tuple[int, int, bytes]]:
    """(key, pos, bytes) of a segment's strings by their second anchors."""
    at, lo, _ = unpack(pos)
    h, near, first, last = anchors(seg, 1, at - lo)
    mixed = (h ^ np.uint64(key * 0x9E3779B97F4A7C15 & (1 << 64) - 1)).view(np.int64)
    return [(k, int(pack(lo + n, lo + a, lo + b)), seg[a : b + LENGTH]) for k, n, a, b in zip(mixed.tolist(), near.tolist(), first.tolist(), last.tolist())]


def _later(strings: list[tuple[int, int]]) -> list[tuple]:
    """Marks for starts (ord, start), as runs."""
    runs: list[list[int]] = []
    for o, x in sorted(strings):
        if runs and runs[-1][0] == o and runs[-1][2] == x - 1:
            runs[-1][2] = x
        else:
            runs.append([o, x, x])
    return [(MARK, 0, o, a, b, None) for o, a, b in runs]


def _compare(batches, level: int, most: int, held_strings: int):
    """Segments sorted by key: marks of each class, or of classes with over ``most`` segments finer ones, after the
    second level single strings. Of equal strings that one task takes apart only the earliest goes on."""
    from xxhash import xxh3_64_intdigest

    held: list[tuple[int, int, bytes]] = []
    key, over, out = None, False, []
    earliest: dict[bytes, tuple[int, int]] = {}
    late: list[tuple[int, int]] = []

    def pass_on():
        out.extend((STRING, (n := xxh3_64_intdigest(x)) - (n >> 63 << 64), o, at, 0, x) for x, (o, at) in earliest.items())
        out.extend(_later(late))
        earliest.clear()
        late.clear()

    def apart():
        for o, pos, seg in held:
            if level == 1:
                out.extend((SEGMENT, k, o, q, 0, part) for k, q, part in finer(key, pos, seg))
                continue
            _, lo, hi = unpack(pos)
            for i in range(hi - lo + 1):
                x, now = seg[i : i + LENGTH], (o, lo + i)
                before = earliest.setdefault(x, now)
                if before > now:
                    earliest[x] = now
                    late.append(before)
                elif before != now:
                    late.append(now)
            if len(earliest) + len(late) > held_strings:
                pass_on()
        held.clear()

    def settle():
        if over:
            apart()
        elif len(held) > 1:
            out.extend((MARK, 0, o, a, b, None) for o, a, b in class_marks(held))
        held.clear()

    for batch in batches:
        for at in range(0, batch.num_rows, 2048):
            for k, o, p, seg in zip(*(c.to_pylist() for c in batch.slice(at, 2048).columns)):
                if k != key:
                    settle()
                    key, over = k, False
                held.append((o, p, seg))
                if len(held) > most:
                    over = True
                    apart()
                if len(out) > 20_000:
                    yield _batch(_STEP, *zip(*out))
                    out.clear()
    settle()
    pass_on()
    for at in range(0, len(out), 20_000):
        yield _batch(_STEP, *zip(*out[at : at + 20_000]))


def _compare_strings(batches):
    """Strings sorted by key, ord and start: marks for all but the first of equal bytes."""
    key, first, late = None, set(), []
    for batch in batches:
        for at in range(0, batch.num_rows, 2048):
            for k, o, p, x in zip(*(c.to_pylist() for c in batch.slice(at, 2048).columns)):
                if k != key:
                    key, first = k, set()
                if x in first:
                    late.append((o, p))
                first.add(x)
            if len(late) > 20_000:
                yield _batch(_STEP, *zip(*_later(late)))
                late = []
    if late:
        yield _batch(_STEP, *zip(*_later(late)))


# --- whole corpus -------------------------------------------------------------------------------


def _remove(batches, ddl: str, keep_text: bool):
    from hashlib import sha256

    for batch in batches:
        out = []
        for doc_id, buf, firsts, lasts in zip(*batch.columns):
            buf = buf.as_py()
            kept, removed, spans, past, end = [], 0, 0, 0, -1
            if firsts.is_valid:
                first, last = np.array(firsts.as_py()), np.array(lasts.as_py())
                by = np.argsort(first, kind="stable")
                first, stop = first[by], np.maximum.accumulate(last[by] + LENGTH)
                new = np.append(True, first[1:] > stop[:-1])
                starts = first[new]
                stops = stop[np.append(np.flatnonzero(new)[1:] - 1, len(stop) - 1)]
                for a, b in zip(starts.tolist(), stops.tolist()):
                    kept.append(buf[past:a])
                    removed += b - a
                    past = b
                spans = len(starts)
            kept.append(buf[past:])
            whole = b"".join(kept)
            out.append((doc_id.as_py(), len(buf), removed, spans, whole if keep_text else sha256(whole).hexdigest()))
        if out:
            yield _batch(ddl, *zip(*out))


def remove_repeats(docs: DataFrame, scratch: Scratch, keep_text: bool = False, class_rows: int = CLASS_ROWS, piece: int = PIECE, held_strings: int = HELD_STRINGS) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_removed, n_spans (maximal removed runs) and kept_sha256, or
    with ``keep_text`` the remaining bytes as ``kept``.

    Null texts are empty; texts under 100 bytes lose nothing; matches never cross documents and are judged
    on the input. Null ids come last; rows that share an id come in the order of a hash of their text, and
    of equal rows one comes first and the rest go. An empty table gives no rows; other columns are not
    read. ``class_rows``, ``piece`` and ``held_strings`` bound what a task holds and change no result.
    """
    spark = docs.sparkSession
    ship(spark)
    rows = docs.select("doc_id", F.col("doc_id").cast("long").alias("ord"), raw_text().alias("text"))
    total, ids = docs.agg(F.count(F.lit(1)), F.count_distinct("doc_id")).first()
    if total != ids:  # an order of rows that ids alone do not give
        rows = scratch.keep(rows.orderBy(F.col("doc_id").asc_nulls_last(), F.md5("text")).withColumn("ord", F.monotonically_increasing_id()), "ordered")
    segments = rows.select("ord", "text").where(F.octet_length("text") >= LENGTH).mapInArrow(tidy(lambda batches: _cut(batches, piece)), _FOUND)
    found = scratch.keep(segments.repartition("key").sortWithinPartitions("key", "high", "low", "ord", "pos").mapInArrow(tidy(_classes), "kind int, key long, ord long, pos long"), "found")
    wanted = found.where(F.col("kind") == SEGMENT).groupBy(F.col("ord").alias("o")).agg(F.collect_list(F.struct("key", "pos")).alias("wanted"))
    sent = rows.join(wanted, F.col("ord") == F.col("o")).select("ord", "text", "wanted").mapInArrow(tidy(_fetch), _STEP)
    at, low = F.shiftright("pos", 16), F.shiftright("pos", 8).bitwiseAND(F.lit(255))
    marks = found.where(F.col("kind") == MARK).select("ord", (at - low).alias("first"), (at - low + F.col("pos").bitwiseAND(F.lit(255))).alias("last"))

    def level(df: DataFrame, n: int) -> DataFrame:
        by_key = df.select("key", "ord", "pos", "bytes").repartition("key").sortWithinPartitions("key")
        return scratch.keep(by_key.mapInArrow(tidy(lambda batches: _compare(batches, n, class_rows, held_strings)), _STEP), f"level-{n}")

    one = level(sent, 1)
    two = level(one.where(F.col("kind") == SEGMENT), 2)
    strings = two.where(F.col("kind") == STRING).select("key", "ord", "pos", "bytes").repartition("key").sortWithinPartitions("key", "ord", "pos")
    for more in (one.where(F.col("kind") == MARK), two.where(F.col("kind") == MARK), strings.mapInArrow(_compare_strings, _STEP)):
        marks = marks.union(more.select("ord", F.col("pos").alias("first"), "last"))
    marks = marks.groupBy(F.col("ord").alias("o")).agg(F.collect_list(F.struct("first", "last")).alias("m"))
    ddl = f"doc_id long, n_bytes long, n_removed long, n_spans long, {'kept binary' if keep_text else 'kept_sha256 string'}"
    joined = rows.join(marks, F.col("ord") == F.col("o"), "left").select("doc_id", "text", F.col("m.first").alias("first"), F.col("m.last").alias("last"))
    return joined.mapInArrow(lambda batches: _remove(batches, ddl, keep_text), ddl)
