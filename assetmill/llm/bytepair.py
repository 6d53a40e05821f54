"""Byte-pair encoding and decoding by dynamic programming over prefixes.

For every prefix of a piece the last token of its encoding is unique. A token that ends the prefix is
that last token exactly if it is compatible with the last token of the shorter prefix in front of it,
so one pass over the matches of the vocabulary's automaton fills a table of last tokens, and following
it backwards gives the ids. No merges are replayed.

Two neighbouring tokens are compatible if encoding their bytes together leaves both standing. Walking
their facing edges from single bytes upwards in the order in which merges happen, they are not if at
some point the two facing parts would merge with each other before either is merged into its own token.
"""

from __future__ import annotations

import gc
import json
import os
import re
import unicodedata
from array import array
from functools import cache
from itertools import chain, compress

import numpy as np
from pyspark.sql import DataFrame

from assetmill.llm.batches import held, map_slices, raw_text

# How byte-level vocabularies cut a text into pieces ({L}, {N}, {S}: letters, numbers, spaces), their
# printable bytes, their spaces, and the letters and numbers that Unicode 16 has over 15.1.
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d| ?[{L}]+| ?[{N}]+| ?[^{S}{L}{N}]+|[{S}]+(?![^{S}])|[{S}]+"
PRINTABLE = (range(33, 127), range(161, 173), range(174, 256))
SPACES = ((0x9, 0xD), (0x20, 0x20), (0x85, 0x85), (0xA0, 0xA0), (0x1680, 0x1680), (0x2000, 0x200A), (0x2028, 0x2029), (0x202F, 0x202F), (0x205F, 0x205F), (0x3000, 0x3000))
LETTERS_16 = (
    (0x1C89, 0x1C8A), (0xA7CB, 0xA7CD), (0xA7DA, 0xA7DC), (0x105C0, 0x105F3), (0x10D4A, 0x10D65), (0x10D6F, 0x10D85), (0x10EC2, 0x10EC4), (0x11380, 0x11389), (0x1138B, 0x1138B), (0x1138E, 0x1138E), (0x11390, 0x113B5),
    (0x113B7, 0x113B7), (0x113D1, 0x113D1), (0x113D3, 0x113D3), (0x11BC0, 0x11BE0), (0x13460, 0x143FA), (0x16100, 0x1611D), (0x16D40, 0x16D6C), (0x18CFF, 0x18CFF), (0x1E5D0, 0x1E5ED), (0x1E5F0, 0x1E5F0),
)
NUMBERS_16 = ((0x10D40, 0x10D49), (0x116D0, 0x116E3), (0x11BF0, 0x11BF9), (0x16130, 0x16139), (0x16D70, 0x16D79), (0x1CCF0, 0x1CCF9), (0x1E5F1, 0x1E5FA))

#: Bytes of encodings that a worker remembers between batches, by the sizes of its objects, and the longest text of one.
CACHED_BYTES, CACHED_LENGTH = 16 << 20, 64
#: Pieces beyond this many bytes are encoded one by one; the pairs of tokens that these remember.
LONG, PLAIN_PAIRS = 256, 100_000
#: Places, as a power of two, for pairs of tokens whose compatibility a worker remembers.
PAIR_BITS = 18
#: Places, a power of two, for what tells a worker that a piece came before.
MET = 1 << 20
#: What an entry of a table takes besides its key and value.
_ENTRY = 104
_NEVER, _SPREAD = (1 << 31) - 1, np.uint64(0x9E3779B97F4A7C15)


def byte_letters() -> list[str]:
    """The letter that stands for each byte: itself if printable, else the next from 256 on."""
    keep, out, more = {b for r in PRINTABLE for b in r}, [], 256
    for b in range(256):
        out.append(chr(b if b in keep else more))
        more += b not in keep
    return out


def _ranges(kind: str, more: tuple[tuple[int, int], ...]) -> list[tuple[int, int]]:
    """Code points of a general category as this Python knows it, and ``more``."""
    has = bytearray(unicodedata.category(chr(i))[0] == kind for i in range(0x110000))
    for a, b in more:
        has[a : b + 1] = b"\1" * (b + 1 - a)
    return [(m.start(), m.end() - 1) for m in re.finditer(b"\1+", bytes(has))]


@cache
def piece_pattern(plain: bool) -> re.Pattern:
    """Cuts a text into pieces; ``plain`` serves ASCII texts only. The classes are those of Unicode 16."""
    if plain:
        return re.compile(PIECES.format(L="A-Za-z", N="0-9", S=r"\t-\r "))
    name = lambda ranges: "".join(f"\\U{a:08X}-\\U{b:08X}" for a, b in ranges)
    return re.compile(PIECES.format(L=name(_ranges("L", LETTERS_16)), N=name(_ranges("N", NUMBERS_16)), S=name(SPACES)))


class Table:
    """A fixed map from numbers below 2^63 to numbers of 32 bits, looked up many at a time; -1 if absent."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        bits = max(4, (4 * len(keys) - 1).bit_length())
        self.shift = np.uint64(64 - bits)
        self.keys, self.values = np.full(1 << bits, -1, dtype=np.int64), np.full(1 << bits, -1, dtype=np.int32)
        left = np.arange(len(keys))
        at = self._home(keys)
        while len(left):
            free = left[self.keys[at] == -1]
            spot = at[self.keys[at] == -1]
            self.keys[spot] = keys[free]  # of several for one place the last stays
            self.values[spot] = values[free]
            lost = self.keys[at] != keys[left]
            left, at = left[lost], (at[lost] + 1) & (len(self.keys) - 1)

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return (keys.view(np.uint64) * _SPREAD >> self.shift).view(np.int64)

    def __call__(self, keys: np.ndarray) -> np.ndarray:
        at = self._home(keys)
        found, out = self.keys[at], self.values[at]
        other = np.flatnonzero((found != keys) & (found != -1))
        while len(other):
            at[other] = (at[other] + 1) & (len(self.keys) - 1)
            now = self.keys[at[other]]
            out[other] = self.values[at[other]]
            found[other] = now
            other = other[(now != keys[other]) & (now != -1)]
        return out

    def items(self):
        here = self.keys >= 0
        return zip(self.keys[here].tolist(), self.values[here].tolist())


class Edges:
    """The parts on one edge of each token, from its byte to itself, each with the rank of the merge that
    takes it into the next."""

    def __init__(self, inner: list[int], rank: list[int], words: dict[bytes, int]):
        self.start = np.zeros(len(inner), dtype=np.int32)
        part: list[int] = []
        until: list[int] = []
        for token in words.values():
            spine, now, take = [], token, _NEVER
            while True:
                spine.append((now, take))
                if inner[now] < 0:
                    break
                take, now = rank[now], inner[now]
            self.start[token] = len(part)
            part += [x for x, _ in reversed(spine)]
            until += [r for _, r in reversed(spine)]
        self.part, self.until = np.array(part, dtype=np.int32), np.array(until, dtype=np.int32)


class BytePairs:
    """Encoder and decoder for a tokenizer file of byte-level byte pairs. It is built once, on the driver;
    workers get its tables, which are flat arrays, and remember the words of a bounded number of bytes."""

    def __init__(self, source: bytes, cached_bytes: int = CACHED_BYTES):
        spec = json.loads(source)
        letters = {c: b for b, c in enumerate(byte_letters())}
        as_bytes = lambda s: bytes(letters[c] for c in s)
        model = spec["model"]
        ids = {as_bytes(t): i for t, i in model["vocab"].items() if all(c in letters for c in t)}
        self.special = {x["content"]: x["id"] for x in spec["added_tokens"]}
        bytes_of = {i: b for b, i in ids.items()} | {i: s.encode() for s, i in self.special.items()}
        if any(bytes([b]) not in ids for b in range(256)):
            raise ValueError("not a byte-level vocabulary: some byte has no token")
        count = max(bytes_of) + 1
        if count > 1 << 20:
            raise ValueError("more than 2^20 tokens")
        self.bytes_of = [bytes_of.get(i, b"") for i in range(count)]
        self.size = np.array([len(b) for b in self.bytes_of], dtype=np.int32)
        self.code = np.dtype(np.uint16 if count <= 1 << 16 else np.uint32)
        merges: dict[int, int] = {}
        first, second, rank = [-1] * count, [-1] * count, [-1] * count
        for r, m in enumerate(model["merges"]):
            a, b = (as_bytes(x) for x in (m.split(" ") if isinstance(m, str) else m))
            whole, left, right = ids[a + b], ids[a], ids[b]
            merges[left << 20 | right] = r
            if first[whole] < 0:
                first[whole], second[whole], rank[whole] = left, right, r
        self.merges = Table(np.array(list(merges), dtype=np.int64), np.array(list(merges.values()), dtype=np.int32))
        words = {b: i for b, i in ids.items() if len(b) == 1}
        longer = sorted(((b, i) for b, i in ids.items() if first[i] >= 0), key=lambda x: len(x[0]))
        self.left, self.right = Edges(first, rank, ids), Edges(second, rank, ids)
        # a token is sound if its parts are and meet whole
        meet = self._apart(np.array([first[i] for _, i in longer], dtype=np.int64), np.array([second[i] for _, i in longer], dtype=np.int64), top=True)
        sound = set(words.values())
        for (b, i), whole in zip(longer, meet.tolist()):
            if whole and first[i] in sound and second[i] in sound:
                sound.add(i)
                words[b] = i
        self._automaton(words)
        self._ready(cached_bytes)

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("special_split", "pairs", "fit", "known", "bare", "used", "met", "marks", "digits", "_plain")}

    def __setstate__(self, state):
        self.__dict__.update(state)
        self._ready(self.cached_bytes)

    def _ready(self, cached_bytes: int) -> None:
        self.cached_bytes = cached_bytes
        self.digits = [str(i) for i in range(len(self.bytes_of))]
        self.special_split = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.pairs, self.fit = np.full(1 << PAIR_BITS, -1, dtype=np.int64), np.zeros(1 << PAIR_BITS, dtype=bool)
        #: Ids by what follows a space, and by whole piece.
        self.known: dict[str, bytes] = {}
        self.bare: dict[str, bytes] = {}
        self.used = 0
        #: Which pieces came before, by some bits of a hash, and how many places are marked.
        self.met, self.marks = np.zeros(MET, dtype=bool), 0
        self._plain: tuple[dict[int, int], dict[int, bool]] | None = None

    def _automaton(self, words: dict[bytes, int]) -> None:
        """The matching automaton as flat tables. A step is state << 8 | byte; ``suffix`` leads a state to the
        longest proper suffix that is a state, ``ends`` to the longest token that ends there, and
        ``shorter`` a token to the next shorter token that ends where it does."""
        step: dict[int, int] = {}
        came: list[tuple[int, int]] = [(0, 0)]
        exact = [-1]
        for word in sorted(words, key=len):
            state = 0
            for byte in word:
                key = state << 8 | byte
                state = step.get(key, -1)
                if state < 0:
                    state = step[key] = len(came)
                    came.append((key >> 8, byte))
                    exact.append(-1)
            exact[state] = words[word]
        suffix, ends, shorter = [0] * len(came), [-1] * len(came), [-1] * len(self.size)
        # a parent's depth is one less, so going by depth finds its suffix known
        depth = [0] * len(came)
        for state in range(1, len(came)):
            depth[state] = depth[came[state][0]] + 1
        for state in sorted(range(1, len(came)), key=depth.__getitem__):
            parent, byte = came[state]
            if parent:
                at = suffix[parent]
                while at and at << 8 | byte not in step:
                    at = suffix[at]
                suffix[state] = step.get(at << 8 | byte, 0)
            below = ends[suffix[state]]
            ends[state] = below if exact[state] < 0 else exact[state]
            if exact[state] >= 0:
                shorter[exact[state]] = below
        self.step = Table(np.array(list(step), dtype=np.int64), np.array(list(step.values()), dtype=np.int32))
        self.suffix, self.ends, self.shorter = (np.array(x, dtype=np.int32) for x in (suffix, ends, shorter))

    def _apart(self, a: np.ndarray, b: np.ndarray, top: bool = False) -> np.ndarray:
        """Whether the tokens of each pair stay apart; with ``top``, whether they meet whole."""
        out = np.ones(len(a), dtype=bool)
        i, j, left = self.right.start[a], self.left.start[b], np.arange(len(a))
        while len(left):
            x, x_until, y, y_until = self.right.part[i], self.right.until[i], self.left.part[j], self.left.until[j]
            whole = (x_until == _NEVER) & (y_until == _NEVER)
            r = self.merges(x.astype(np.int64) << 20 | y)
            # of equal merges the leftmost comes first: x's own is left of this one, y's own is right of it
            met = (r >= 0) & (r < x_until) & (r <= y_until)
            if top:
                met &= ~whole
            out[left[met]] = False
            on = ~(met | whole)
            left, i, j, x_until, y_until = left[on], i[on], j[on], x_until[on], y_until[on]
            up = x_until <= y_until
            i, j = i + up, j + ~up
        return out

    def _fits(self, pair: np.ndarray) -> np.ndarray:
        """``_apart`` of pairs a << 20 | b, by way of a table in which a place holds the pair that came last."""
        at = (pair.view(np.uint64) * _SPREAD >> np.uint64(64 - PAIR_BITS)).view(np.int64)
        out, new = self.fit[at], np.flatnonzero(self.pairs[at] != pair)
        if len(new):
            asked, back = np.unique(pair[new], return_inverse=True)
            found = self._apart(asked >> 20, asked & 0xFFFFF)
            out[new] = found[back]
            at = (asked.view(np.uint64) * _SPREAD >> np.uint64(64 - PAIR_BITS)).view(np.int64)
            self.pairs[at], self.fit[at] = asked, found
        return out

    def encode_short(self, pieces: list[bytes]) -> list[bytes]:
        """Packed ids of each piece, none empty, all in step with each other: ``last`` holds the last token of each
        prefix by its length, the empty one first."""
        n, lengths = len(pieces), np.array([len(p) for p in pieces], dtype=np.int64)
        by = np.argsort(-lengths, kind="stable")
        lengths, most = lengths[by], int(lengths.max())
        text = np.array(pieces, dtype=f"S{most}").view(np.uint8).reshape(n, most)[by].T.astype(np.int64)
        last = np.full((most + 1, n), -1, dtype=np.int32)
        flat, state, size = last.reshape(-1), np.zeros(n, dtype=np.int64), self.size
        going = np.searchsorted(-lengths, -np.arange(most), side="left")  # how many are longer than each prefix
        for t in range(most):
            m = int(going[t])
            byte, now = text[t, :m], state[:m]
            after = self.step(now << 8 | byte).astype(np.int64)
            lost = np.flatnonzero(after < 0)
            while len(lost):
                now[lost] = self.suffix[now[lost]]
                after[lost] = self.step(now[lost] << 8 | byte[lost])
                lost = lost[after[lost] < 0]
            state[:m] = after
            token = self.ends[after]
            start = t + 1 - size[token].astype(np.int64)
            ask = np.flatnonzero(start > 0)
            while len(ask):
                before = flat[start[ask] * n + ask].astype(np.int64)
                ask = ask[~self._fits(before << 20 | token[ask])]
                token[ask] = self.shorter[token[ask]]
                start[ask] = t + 1 - size[token[ask]]
                ask = ask[start[ask] > 0]
            last[t + 1, :m] = token
        at, here, turns = lengths.copy(), np.arange(n), []
        while len(here):
            token = flat[at[here] * n + here]
            turns.append((here, token))
            at[here] -= size[token]
            here = here[at[here] > 0]
        count = np.zeros(n, dtype=np.int64)
        for here, _ in turns:
            count[here] += 1
        stop = np.cumsum(count)
        ids = np.empty(int(stop[-1]), dtype=self.code)
        for turn, (here, token) in enumerate(turns):
            ids[stop[here] - 1 - turn] = token
        packed, width, out = ids.tobytes(), self.code.itemsize, [b""] * n
        for k, a, b in zip(by.tolist(), ((stop - count) * width).tolist(), (stop * width).tolist()):
            out[k] = packed[a:b]
        return out

    def encode_long(self, piece: bytes) -> bytes:
        """The same for one piece of any length, byte by byte."""
        if self._plain is None:
            self._plain = dict(self.step.items()), {}
        (step, fits), suffix, ends, shorter, size = self._plain, self.suffix.item, self.ends.item, self.shorter.item, self.size.item
        last, state = array("i", [-1]), 0
        for end, byte in enumerate(piece, 1):
            after = step.get(state << 8 | byte)
            while after is None:
                state = suffix(state)
                after = step.get(state << 8 | byte)
            state = after
            token = ends(state)
            start = end - size(token)
            while start:
                pair = last[start] << 20 | token
                fit = fits.get(pair)
                if fit is None:
                    if len(fits) >= PLAIN_PAIRS:
                        fits.clear()
                    fit = fits[pair] = bool(self._fits(np.array([pair], dtype=np.int64))[0])
                if fit:
                    break
                token = shorter(token)
                start = end - size(token)
            last.append(token)
        out, at = array("I"), len(piece)
        while at:
            out.append(last[at])
            at -= size(last[at])
        return np.array(out[::-1]).astype(self.code).tobytes()

    def _encode_pieces(self, pieces: list[str]) -> list[bytes]:
        raw, out = list(map(str.encode, pieces)), [b""] * len(pieces)
        sizes = np.fromiter(map(len, raw), dtype=np.int64, count=len(raw))
        by = np.argsort(sizes, kind="stable")
        sizes, by, at = sizes[by], by.tolist(), 0
        while at < len(by) and sizes[at] <= LONG:
            end = int(np.searchsorted(sizes, min(max(8, 2 * sizes[at]), LONG), side="right"))
            for k, ids in zip(by[at:end], self.encode_short([raw[k] for k in by[at:end]])):
                out[k] = ids
            at = end
        for k in by[at:]:
            out[k] = self.encode_long(raw[k])
        return out

    def _learn(self, spaced: set[str], first: set[str]) -> tuple[dict[str, bytes], dict[str, bytes]]:
        """Ids of chunks that follow a space, and of chunks that do not."""
        known, bare = self.known, self.bare
        new, alone = spaced.difference(known), first.difference(bare)
        after, whole = {w: known[w] for w in spaced.difference(new)}, {p: bare[p] for p in first.difference(alone)}
        hits_w, hits_p = list(after), list(whole)
        words = set(filter(str.isalpha, new))  # what Python calls letters are letters here too
        pieces = set(filter(str.isalpha, alone))
        cut_w = [(w, piece_pattern(w.isascii()).findall(" " + w)) for w in new.difference(words)]
        cut_p = [(p, piece_pattern(p.isascii()).findall(p)) for p in alone.difference(pieces)]
        for _, parts in chain(cut_w, cut_p):
            for p in parts:
                if p[0] == " " and p[1:].isalpha():
                    words.add(p[1:])
                else:
                    pieces.add(p)
        asked_w, asked_p = list(words.difference(known)), list(pieces.difference(bare))
        ids = self._encode_pieces([" " + w for w in asked_w] + asked_p)
        fresh_w, fresh_p = dict(zip(asked_w, ids)), dict(zip(asked_p, ids[len(asked_w) :]))

        def packed(p: str) -> bytes:
            if p[0] == " " and p[1:].isalpha():
                return fresh_w.get(p[1:]) or known[p[1:]]
            return fresh_p.get(p) or bare[p]

        made_w, made_p = ([(text, b"".join(map(packed, parts))) for text, parts in cut] for cut in (cut_w, cut_p))
        self._remember(known, fresh_w)
        self._remember(bare, fresh_p)
        self._forget(hits_w, hits_p)
        after.update(fresh_w)
        whole.update(fresh_p)
        after.update(made_w)
        whole.update(made_p)
        return after, whole

    def encode_all(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of each text. No piece goes across a space that something other than white space follows, so
        texts are cut before such spaces, and each different chunk is encoded once."""
        cut, spaced, first = [], set(), set()
        for text in texts:
            parts = []
            for part in self.special_split.split(text) if self.special_split else [text]:
                if part in self.special:
                    parts.append(self.special[part])
                elif part:
                    head, *rest = _CUT.split(part) if _SPACES.search(part) else part.split(" ")
                    parts.append((head, rest))
                    spaced.update(rest)
                    if head:
                        first.add(head)
            cut.append(parts)
        after, whole = self._learn(spaced, first)
        out = []
        for parts in cut:
            packed: list[bytes] = []
            for p in parts:
                if isinstance(p, int):
                    packed.append(self.code.type(p).tobytes())
                else:
                    packed.append(whole[p[0]] if p[0] else b"")
                    packed += map(after.__getitem__, p[1])
            out.append(np.frombuffer(b"".join(packed), dtype=self.code))
        return out

    def _remember(self, table: dict[str, bytes], fresh: dict[str, bytes]) -> None:
        """Into a table go the pieces that were asked for before, as far as one bit of a hash tells, so that words
        which come once do not drive out those that come often. Long ones are not kept."""
        if not fresh:
            return
        at = np.fromiter(map(hash, fresh), dtype=np.int64, count=len(fresh)) & (len(self.met) - 1)
        again = self.met[at]
        self.met[at] = True
        self.marks += len(at) - int(np.count_nonzero(again))
        if self.marks > len(self.met) // 2:
            self.met[:] = False
            self.marks = 0
        kept = {k: v for k, v in compress(fresh.items(), again.tolist()) if len(k) <= CACHED_LENGTH}
        table.update(kept)
        self.used += _room(kept)

    def _forget(self, words: list[str], pieces: list[str]) -> None:
        """Once the tables are over their bytes, they keep what they could give to the last texts, if that is
        nine tenths of it at most."""
        if self.used <= self.cached_bytes:
            return
        for table, hits in ((self.known, words), (self.bare, pieces)):
            kept = {k: table[k] for k in hits}
            table.clear()
            table.update(kept)
        self.used = _room(self.known) + _room(self.bare)
        if self.used > self.cached_bytes * 9 // 10:
            self.known.clear()
            self.bare.clear()
            self.used = 0

    def encode(self, text: str) -> list[int]:
        return self.encode_all([text])[0].tolist()

    def joined(self, ids: list[int]) -> str:
        """Ids in decimal, joined by commas."""
        return ",".join(map(self.digits.__getitem__, ids))

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.bytes_of.__getitem__, ids)).decode("utf-8", "replace")


_SPACES = re.compile(r" (?:\s|$)")
_CUT = re.compile(r" (?=\S)")


def _room(table: dict[str, bytes]) -> int:
    """Bytes that the entries of a table take."""
    return sum(map(str.__sizeof__, table)) + sum(map(bytes.__sizeof__, table.values())) + _ENTRY * len(table)


@cache
def _built(path: str, changed: float, cached_bytes: int) -> BytePairs:
    with open(path, "rb") as f:
        return BytePairs(f.read(), cached_bytes)


def _sent(docs: DataFrame, path: str, cached_bytes: int = CACHED_BYTES):
    """The tables of a tokenizer file, built on the driver and sent to the workers."""
    return docs.sparkSession.sparkContext.broadcast(_built(path, os.path.getmtime(path), cached_bytes))


def _loaded(sent) -> BytePairs:
    """One table a worker, kept between tasks until another operator's task runs there."""
    loaded = held("bytepair")
    if sent.value not in loaded.values():
        loaded.clear()
        loaded["table"] = sent.value
        gc.freeze()  # the collector need not walk tables and caches; ``held`` undoes this
    return loaded["table"]


def encode(docs: DataFrame, tokenizer_path: str, digest: bool = True) -> DataFrame:
    """One row per document: doc_id, n_tokens, ids and decoded. With ``digest`` the last two are SHA-256
    hex digests (``ids_sha256``, ``decoded_sha256``), else comma-joined ids and the decoded text.

    The driver reads the tokenizer file and sends its tables to the workers. Null texts count as empty and
    have no ids; every row is encoded whole and on its own, so equal rows give equal results; an empty
    table gives none. Other columns are not read.
    """
    sent = _sent(docs, tokenizer_path)

    def make():
        from hashlib import sha256

        table = _loaded(sent)

        def some(doc_ids, bufs):
            for doc_id, found in zip(doc_ids, table.encode_all([b.decode("utf-8", "replace") for b in bufs])):
                ids = found.tolist()
                listed, text = table.joined(ids), table.decode(ids)
                if digest:
                    listed, text = sha256(listed.encode()).hexdigest(), sha256(text.encode()).hexdigest()
                yield doc_id, len(ids), listed, text

        return some

    names = ("ids_sha256", "decoded_sha256") if digest else ("ids", "decoded")
    return map_slices(docs.select("doc_id", raw_text()), make, f"doc_id long, n_tokens long, {names[0]} string, {names[1]} string", "bytepair")


def token_rows(docs: DataFrame, tokenizer_path: str) -> DataFrame:
    """One row per document: doc_id, n_tokens, ids (array of int), decoded_sha256. Nulls and empty texts as
    in ``encode``."""
    sent = _sent(docs, tokenizer_path)

    def make():
        from hashlib import sha256

        table = _loaded(sent)

        def some(doc_ids, bufs):
            for doc_id, ids in zip(doc_ids, table.encode_all([b.decode("utf-8", "replace") for b in bufs])):
                yield doc_id, len(ids), ids.astype(np.int32), sha256(table.decode(ids.tolist()).encode()).hexdigest()

        return some

    return map_slices(docs.select("doc_id", raw_text()), make, "doc_id long, n_tokens long, ids array<int>, decoded_sha256 string", "bytepair")
