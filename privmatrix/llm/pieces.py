"""SentencePiece encoding and decoding as shortest paths through a composed weighted transducer.

A model file is compiled into machines that are arrays: a normaliser (rewrite rules, white space to the meta symbol, dummy prefix), an
automaton of pieces whose final states emit a piece, and a byte fallback that spells any other character. Composing them with
an input runs the automaton from all of its positions at once, which gives a lattice of pieces over these positions; the encoding is the
lattice's path of least weight in the tropical semiring (weights add along a path, the least total wins). Positions are settled from left to
right, for many inputs of one length together.

* Unigram models: a piece weighs minus its score.
* Byte-pair models: an arc weighs 0 if its piece may follow the last piece of the path that leads to its start, else it is infinite. A
  piece may follow another if merging their joined text never joins across their bound. Such a segmentation is unique for every prefix of
  the input, so just one finite path leads to each position and the result equals that of the merge procedure.

Merges across a bound are found from the last one backwards: of the two pieces at the bound, the one that was formed later is undone, until
they would merge before what was undone last, or both are characters. This needs pieces that are formed of better scored ones
only; what may stand in an input that holds other pieces (such as runs of the meta symbol) is found by merging the two.

The lattice is cut where no piece can cross (before a meta symbol that follows another character, and around line breaks). The paths
of such chunks are kept between slices of an input up to a number that bounds memory.

Null texts give a null list and decode to null; empty texts give an empty list. Repeated rows get the same lists; there are
no ties in byte-pair models, and in unigram models the longer last piece wins. Whole texts are encoded, whatever their
length. Extra columns are kept; a column named like the output column is replaced.
"""

from __future__ import annotations

import re
import struct
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from privmatrix.llm import textscan

META = "▁"
NORMAL, UNKNOWN, CONTROL, USER_DEFINED, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
KEPT_CHUNKS = 100_000
PAIR_BITS = 19
WIDTHS = (8, 10, 13, 20, 40)  # chunks up to each of these lengths are settled together, longer ones one by one
TOGETHER = 16_384  # chunks that are settled at once
BATCH_BYTES = 1_000_000
NEVER = 1 << 30


def _fields(data: bytes) -> Iterator[tuple[int, object]]:
    """(number, value) of a protocol buffer message."""

    def varint(at: int) -> tuple[int, int]:
        value = shift = 0
        while True:
            b = data[at]
            value |= (b & 127) << shift
            at, shift = at + 1, shift + 7
            if b < 128:
                return value, at

    at = 0
    while at < len(data):
        key, at = varint(at)
        kind = key & 7
        if kind == 0:
            value, at = varint(at)
        elif kind == 2:
            n, at = varint(at)
            value, at = data[at : at + n], at + n
        else:
            n = {1: 8, 5: 4}[kind]
            value, at = data[at : at + n], at + n
        yield key >> 3, value


class Automaton:
    """Keys over symbols 0..n-1 as a deterministic automaton in two arrays: from state s, symbol c leads to base[s] + c if that state's owner is s.

    Symbol n stands for all others. ``emits`` holds each state's key number, or -1.
    """

    def __init__(self, keys: list[tuple[int, ...]], symbols: int):
        children: list[dict[int, int]] = [{}]
        final: dict[int, int] = {}
        for number, key in enumerate(keys):
            node = 0
            for c in key:
                if c not in children[node]:
                    children[node][c] = len(children)
                    children.append({})
                node = children[node][c]
            final[node] = number
        size = 2 * symbols + 4 * len(children) + 16
        base, owner, emits = np.zeros(size, np.int32), np.full(size, -1, np.int32), np.full(size, -1, np.int32)
        place, free, low = {0: 0}, bytearray(size), 1
        free[0] = 1
        order = [0]
        for node in order:
            order += children[node].values()
        # states stay in order of depth, so that a state is placed before its children
        for node in order:
            own = place[node]
            emits[own] = final.get(node, -1)
            codes = sorted(children[node])
            if not codes:
                continue
            while free[low]:
                low += 1
            b = max(1, low - codes[0])
            while any(free[b + c] for c in codes):
                b += 1
                while free[b + codes[0]]:
                    b += 1
            base[own] = b
            for c in codes:
                free[b + c] = 1
                owner[b + c] = own
                place[children[node][c]] = b + c
        last = max(place.values()) + symbols + 2
        self.base, self.owner, self.emits, self.other = base[:last], owner[:last], emits[:last], symbols
        self.dead = last - 1  # no state's
        self.base[self.dead] = 0
        self.owner[self.dead] = -1

    def step(self, state: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        to = self.base[state] + symbol
        return np.where(self.owner[to] == state, to, self.dead)


class Model:
    """The compiled machines of a model file."""

    def __init__(self, data: bytes):
        self.pieces: list[str] = []
        self.scores: list[float] = []
        self.kinds: list[int] = []
        self.bpe, self.prefix, self.squeeze, self.escape = False, True, True, True
        charsmap = b""
        for number, value in _fields(data):
            if number == 1:
                piece = dict(_fields(value))
                self.pieces.append(piece.get(1, b"").decode())
                self.scores.append(struct.unpack("<f", piece[2])[0] if 2 in piece else 0.0)
                self.kinds.append(piece.get(3, NORMAL))
            elif number == 2:
                self.bpe = dict(_fields(value)).get(3, 1) == 2
            elif number == 3:
                spec = dict(_fields(value))
                charsmap = spec.get(2, b"")
                self.prefix, self.squeeze, self.escape = bool(spec.get(3, 1)), bool(spec.get(4, 1)), bool(spec.get(5, 1))
        rules = sorted(self._charsmap(charsmap).items())
        self._rewrites = [target for _, target in rules]
        self._normaliser = Automaton([tuple(key) for key, _ in rules], 256) if rules else None
        self.n = len(self.pieces)
        self.unknown = self.kinds.index(UNKNOWN)
        self.bytes = {int(p[3:5], 16): i for i, (p, k) in enumerate(zip(self.pieces, self.kinds)) if k == BYTE}
        self.id = {p: i for i, (p, k) in enumerate(zip(self.pieces, self.kinds)) if k in (NORMAL, USER_DEFINED)}
        self._lowest = min(self.scores, default=0.0) - 10.0
        crossing = any(re.search(f"[^{META}]{META}", p) for p in self.id)
        self._chunks = None if crossing else re.compile(f"{META}*[^{META}\n]+|{META}+|\n" if not any("\n" in p for p in self.id) else f"{META}*[^{META}]+|{META}+")
        odd = self._undo() if self.bpe else []
        self._odd = re.compile("|".join(map(re.escape, sorted(odd, key=len)))) if 0 < len(odd) <= 1000 else re.compile("" if odd else "(?!)")
        used = [p for p, i in self.id.items() if len(p) == 1 or not self.bpe or self._left[i] >= 0] + odd
        letters = sorted({ord(c) for p in used for c in p})
        self._letter = np.full(0x110000, len(letters), np.uint16 if len(letters) < 65535 else np.int32)
        self._letter[letters] = np.arange(len(letters))
        self._machine = Automaton([tuple(self._letter[[ord(c) for c in p]].tolist()) for p in used], len(letters))
        self._emits = np.append(np.array([self.id[p] for p in used], np.int32), np.int32(-1))[self._machine.emits]
        self._reach = max(map(len, used), default=1)
        self._weight = -np.append(np.array(self.scores, np.float64), self._lowest)
        surface = [bytes([int(p[3:5], 16)]) if k == BYTE else " ⁇ ".encode() if k == UNKNOWN else b"" if k == CONTROL else p.replace(META, " ").encode() for p, k in zip(self.pieces, self.kinds)]
        self._surface = np.frombuffer(b"".join(surface), np.uint8)
        self._surface_at = np.concatenate(([0], np.cumsum([len(x) for x in surface])))
        self.forget()

    @staticmethod
    def _charsmap(blob: bytes) -> dict[bytes, bytes]:
        """The normaliser's rewrite rules, read from its double-array trie."""
        if not blob:
            return {}
        n = struct.unpack("<I", blob[:4])[0]
        units, target, rules = struct.unpack(f"<{n // 4}I", blob[4 : 4 + n]), blob[4 + n :], {}
        offset = lambda u: (u >> 10) << ((u & (1 << 9)) >> 6)
        todo = [(offset(units[0]), b"")]
        while todo:
            base, key = todo.pop()
            for c in range(256):
                if (at := base ^ c) >= len(units):
                    continue
                u = units[at]
                if c == 0 and u >> 31:
                    a = u & 0x7FFFFFFF
                    rules[key] = target[a : target.index(b"\0", a)]
                elif c and u & 0x800000FF == c:
                    grown = key + bytes([c])
                    if u >> 8 & 1:
                        leaf = units[at ^ offset(u)] if (at ^ offset(u)) < len(units) else 0
                        if leaf >> 31:
                            a = leaf & 0x7FFFFFFF
                            rules[grown] = target[a : target.index(b"\0", a)]
                    todo.append((at ^ offset(u), grown))
        return rules

    def normalised(self, text: str) -> str:
        if self._normaliser:
            text = self._rewritten(text)
        if self.squeeze:
            text = re.sub(" +", " ", text.strip(" "))
        if text and self.prefix:
            text = " " + text
        return text.replace(" ", META) if self.escape else text

    def _rewritten(self, text: str) -> str:
        """The normaliser composed with a text: from each position the longest rule that fits, else the character itself."""
        whole = text.encode()
        data = np.frombuffer(whole, np.uint8).astype(np.int32)
        rule, span, machine = np.full(len(data), -1), np.zeros(len(data), np.int64), self._normaliser
        at, state, n = np.arange(len(data)), np.zeros(len(data), np.int32), 0
        while len(at):
            state = machine.step(state, data[at + n])
            n += 1
            found = machine.emits[state]
            rule[at[found >= 0]], span[at[found >= 0]] = found[found >= 0], n
            live = (state != machine.dead) & (at + n < len(data))
            at, state = at[live], state[live]
        out, done = [], 0
        for i in np.flatnonzero((rule >= 0) & (data & 0xC0 != 0x80)).tolist():
            if i >= done:
                out += [whole[done:i], self._rewrites[rule[i]]]
                done = i + int(span[i])
        return b"".join([*out, whole[done:]]).decode(errors="replace")

    # --- what may follow what in a byte-pair model

    def _undo(self) -> list[str]:
        """Sets the rank of each piece's merge and the two pieces that it joins; a character's rank is -1, a piece that merging never gives has no parts. Returns the pieces that are formed of worse ones or equals."""
        odd: list[str] = []
        ranks, left, right, joins = [-1] * (self.n + 1), [-1] * (self.n + 1), [-1] * (self.n + 1), {}
        whole = [p for p in self.id if len(p) > 1]
        order = {s: k for k, s in enumerate(sorted({self.scores[self.id[p]] for p in whole}, reverse=True))}
        for p in whole:
            ranks[self.id[p]] = order[self.scores[self.id[p]]]
        for p in whole:
            for k in range(1, len(p)):
                a, b = self.id.get(p[:k]), self.id.get(p[k:])
                if a is not None and b is not None:
                    joins[a << 32 | b] = ranks[self.id[p]]

        def apart(a: int, b: int, limit: int) -> bool:
            """Whether no merge of a rank below ``limit`` joins across the bound of two pieces."""
            while joins.get(a << 32 | b, NEVER) >= limit:
                if ranks[a] > ranks[b]:
                    limit, a = ranks[a], right[a]
                elif ranks[b] >= 0:
                    limit, b = ranks[b] + 1, left[b]
                else:
                    return True
            return False

        for p in sorted(whole, key=lambda p: (ranks[self.id[p]], len(p))):
            i = self.id[p]
            for k in range(1, len(p)):
                a, b = self.id.get(p[:k]), self.id.get(p[k:])
                formed = a is not None and b is not None and all(len(self.pieces[x]) == 1 or left[x] >= 0 for x in (a, b))
                if formed and max(ranks[a], ranks[b]) < ranks[i] and apart(a, b, ranks[i]):
                    left[i], right[i] = a, b
                    break
            else:
                odd += [p] if self._merged(p) == [p] else []
        self._rank, self._left, self._right = (np.array(x, np.int64) for x in (ranks, left, right))
        keys = np.array(sorted(joins), np.int64)
        self._join_keys = np.append(keys, NEVER << 32)
        self._join_ranks = np.append(np.array([joins[k] for k in keys.tolist()], np.int64), NEVER)
        return odd

    def _all_apart(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether no merge joins across the bounds of pairs of pieces."""
        ok, row, limit = np.ones(len(a), bool), np.arange(len(a)), np.full(len(a), NEVER)
        while len(row):
            key = a << 32 | b
            at = np.searchsorted(self._join_keys, key)
            joined = (self._join_keys[at] == key) & (self._join_ranks[at] < limit)
            ok[row[joined]] = False
            x, y = self._rank[a], self._rank[b]
            first = x > y
            go = ~joined & (first | (y >= 0))
            limit = np.where(first, x, y + 1)[go]
            row, a, b = row[go], np.where(first, self._right[a], a)[go], np.where(first, b, self._left[b])[go]
        return ok

    def _may_follow(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """``_all_apart`` with a table of verdicts, each of which the next pair of its place replaces. Symbols without a piece stand anywhere."""
        a, b = np.minimum(a, self.n).astype(np.int64), np.minimum(b, self.n).astype(np.int64)
        key = a << 32 | b
        at = (key * np.int64(-7046029254386353131)) >> np.int64(64 - PAIR_BITS) & np.int64((1 << PAIR_BITS) - 1)
        held = self._pairs[at]
        miss = np.flatnonzero(held >> 1 != key)
        if len(miss):
            once, back = np.unique(key[miss], return_inverse=True)
            held[miss] = (once << 1 | self._all_apart(once >> 32, once & 0xFFFFFFFF))[back]
            self._pairs[at[miss]] = held[miss]
        return (held & 1).astype(bool)

    def _merged(self, text: str) -> list[str]:
        """Byte-pair merging of a text, best score first, leftmost of equals."""
        parts = list(text)
        while True:
            best, at = None, -1
            for i in range(len(parts) - 1):
                p = self.id.get(parts[i] + parts[i + 1])
                if p is not None and (best is None or self.scores[p] > best):
                    best, at = self.scores[p], i
            if best is None:
                return parts
            parts[at : at + 2] = [parts[at] + parts[at + 1]]

    # --- shortest paths

    def _lattice(self, letters: np.ndarray, points: np.ndarray) -> list[np.ndarray]:
        """Inputs of one length (rows) composed with the pieces: for each piece length the piece that starts at each position, or -1. A character without a piece is a symbol above all pieces."""
        state, out = np.zeros(letters.shape, np.int32), []
        for n in range(1, min(self._reach, letters.shape[1]) + 1):
            state = self._machine.step(state[:, : letters.shape[1] - n + 1], letters[:, n - 1 :])
            found = self._emits[state]
            out.append(found if n > 1 else np.where(found < 0, self.n + points, found).astype(np.int32))
        return out

    def _settled(self, points: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Shortest paths of inputs (rows of code points, the longest first, padded): the last piece of the path to each position, and its length."""
        rows, width = points.shape
        last, span = np.full((width + 1, rows), -1, np.int32), np.zeros((width + 1, rows), np.int8)
        weight = np.full((width + 1, rows), np.inf)
        weight[0] = 0
        arcs: list[list[tuple[int, np.ndarray, np.ndarray]]] = [[] for _ in range(width + 1)]  # of each position: length, rows and pieces of what ends there
        for n, found in reversed(list(enumerate(self._lattice(self._letter[points].astype(np.int32), points), 1))):
            at, row = np.nonzero((found >= 0).T)
            piece = found.T[at, row]
            cuts = np.searchsorted(at, np.arange(found.shape[1] + 1)).tolist()
            for i, (x, y) in enumerate(zip(cuts[:-1], cuts[1:])):
                if y > x:
                    arcs[i + n].append((n, row[x:y], piece[x:y]))
        live = np.searchsorted(-length, -np.arange(width + 1), "right")
        for j in range(1, width + 1):
            for n, row, piece in arcs[j]:  # longest first
                if self.bpe:
                    open_ = np.flatnonzero(last[j, row] < 0) if n > 1 else np.flatnonzero((last[j] < 0) & (np.arange(rows) < live[j]))
                    row, piece = row[open_], piece[open_]
                    if n < j:
                        ok = self._may_follow(last[j - n, row], piece)
                        row, piece = row[ok], piece[ok]
                else:
                    total = weight[j - n, row] + self._weight[np.minimum(piece, self.n)]
                    better = total < weight[j, row]
                    row, piece = row[better], piece[better]
                    weight[j, row] = total[better]
                last[j, row], span[j, row] = piece, n
        return last, span

    def _stands(self, a: int, b: int, odd: bool) -> bool:
        """``_may_follow`` for one pair; by merging the joined text where pieces that are formed of worse ones may be in play."""
        if a >= self.n or b >= self.n:
            return True
        key = (a << 32 | b) << 1 | odd
        ok = self._verdicts.get(key)
        if ok is None:
            if len(self._verdicts) >= KEPT_CHUNKS:
                self._verdicts.clear()
            x, y = self.pieces[a], self.pieces[b]
            ok = self._verdicts[key] = self._merged(x + y) == [x, y] if odd else bool(self._all_apart(np.array([a]), np.array([b]))[0])
        return ok

    def _long(self, text: str, odd: bool) -> list[int]:
        """The shortest path of one input, from the same lattice."""
        points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)[None]
        arcs = [x[0].tolist() for x in self._lattice(self._letter[points].astype(np.int32), points)]
        last, span, weight = [-1] * (len(text) + 1), [0] * (len(text) + 1), [0.0] * (len(text) + 1)
        for j in range(1, len(text) + 1):
            best = float("inf")
            for n in range(min(len(arcs), j), 0, -1):
                if (piece := arcs[n - 1][j - n]) < 0:
                    continue
                if self.bpe:
                    if n < j and not self._stands(last[j - n], piece, odd):
                        continue
                    last[j], span[j] = piece, n
                    break
                total = weight[j - n] + self._weight[min(piece, self.n)]
                if total < best:
                    best = weight[j] = total
                    last[j], span[j] = piece, n
        out, j = [], len(text)
        while j:
            out.append(last[j])
            j -= span[j]
        return out[::-1]

    def _paths(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all chunks' paths joined, their number for each chunk)."""
        counts, found = np.zeros(len(chunks), np.int64), []  # found: chunk, place from the end, symbol
        length = np.fromiter(map(len, chunks), np.int64, len(chunks))
        odd = np.fromiter((x is not None for x in map(self._odd.search, chunks)), bool, len(chunks))
        alone = odd | (length > WIDTHS[-1])
        low = 0
        for width in WIDTHS:
            own = np.flatnonzero(~alone & (length > low) & (length <= width))
            own, low = own[np.argsort(-length[own], kind="stable")], width
            for a in range(0, len(own), TOGETHER):
                part = own[a : a + TOGETHER]
                joined = "".join([chunks[i].ljust(width) for i in part.tolist()])
                points = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64).reshape(-1, width)
                last, span = self._settled(points, length[part])
                row, end, k = np.arange(len(part)), length[part], 0
                while len(row):
                    found.append((part[row], np.full(len(row), k), last[end, row]))
                    counts[part[row]] += 1
                    end = end - span[end, row]
                    row, end, k = row[end > 0], end[end > 0], k + 1
        for i in np.flatnonzero(alone).tolist():
            path = self._long(chunks[i], bool(odd[i]))
            counts[i] = len(path)
            found.append((np.full(len(path), i), np.arange(len(path))[::-1], np.array(path, np.int32)))
        starts = np.concatenate(([0], np.cumsum(counts)))
        flat = np.zeros(int(starts[-1]), np.int32)
        for chunk, back, symbol in found:
            flat[starts[chunk + 1] - 1 - back] = symbol
        strange = np.flatnonzero(flat >= self.n)
        if not len(strange):
            return flat, counts
        out, done = [], 0
        for i in np.unique(np.searchsorted(starts, strange, "right") - 1).tolist():
            spelt = self._spelt(flat[starts[i] : starts[i + 1]].tolist())
            out += [flat[done : starts[i]], np.array(spelt, np.int32)]
            done, counts[i] = starts[i + 1], len(spelt)
        return np.concatenate([*out, flat[done:]]), counts

    def _spelt(self, path: list[int]) -> list[int]:
        """Ids of a path; symbols without a piece become bytes, or the unknown piece (one for a run of them)."""
        out: list[int] = []
        for p in path:
            if p < self.n:
                out.append(p)
            elif self.bytes:
                out += [self.bytes[b] for b in chr(p - self.n).encode()]
            elif not out or out[-1] != self.unknown:
                out.append(self.unknown)
        return out

    def encode(self, text: str) -> list[int]:
        return self.encode_all([text])[0].tolist()

    def encode_all(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts joined, their number for each text)."""
        chunks: list[str] = []
        ends = np.zeros(len(texts) + 1, np.int64)
        for i, text in enumerate(texts):
            text = self.normalised(text)
            chunks += self._chunks.findall(text) if self._chunks else [text] if text else []
            ends[i + 1] = len(chunks)
        if len(self._known) > KEPT_CHUNKS:
            self._drop()
        new = list(set(chunks).difference(self._known))
        flat, counts = self._paths(new)
        self._known.update(zip(new, range(len(self._known), len(self._known) + len(new))))
        self._kept = np.concatenate((self._kept, flat))
        self._kept_at = np.concatenate((self._kept_at, self._kept_at[-1] + np.cumsum(counts)))
        code = np.fromiter(map(self._known.__getitem__, chunks), np.int64, len(chunks))
        starts, size = self._kept_at[code], self._kept_at[code + 1] - self._kept_at[code]
        total = np.concatenate(([0], np.cumsum(size)))
        ids = self._kept[np.repeat(starts - total[:-1], size) + np.arange(total[-1])]
        return ids, np.diff(total[ends])

    def _drop(self) -> None:
        self._known: dict[str, int] = {}
        self._kept, self._kept_at = np.zeros(0, np.int32), np.zeros(1, np.int64)

    def forget(self) -> None:
        """Drop the kept paths; a worker outlives its task and may next serve another operator."""
        self._drop()
        self._pairs = np.full(1 << PAIR_BITS if self.bpe else 0, -1, np.int64)
        self._verdicts = {}

    def decode(self, ids: list[int]) -> str:
        """The text of a list of ids: bytes joined, the meta symbol back to a space, the dummy prefix gone."""
        return self.decode_all(np.array(ids, np.int64), np.array([0, len(ids)]))[0].as_py()

    def decode_all(self, ids: np.ndarray, offsets: np.ndarray) -> pa.Array:
        """The texts of the lists that ``offsets`` cut ``ids`` into."""
        length = np.diff(self._surface_at)[ids]
        ends = np.concatenate(([0], np.cumsum(length)))
        data = self._surface[np.repeat(self._surface_at[ids] - ends[:-1], length) + np.arange(ends[-1])]
        starts, stops = ends[offsets[:-1]], ends[offsets[1:]]
        if self.prefix and len(data):
            starts = starts + ((starts < stops) & (data[np.minimum(starts, len(data) - 1)] == 32))
        whole = data.tobytes()
        return pa.array([whole[a:b].decode(errors="replace") for a, b in zip(starts.tolist(), stops.tolist())], pa.string())


@lru_cache(maxsize=2)
def _compiled(data: bytes) -> Model:
    """A model file's machines, compiled on the driver: compiling takes ten times the memory of what it makes."""
    return Model(data)


def _slices(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    rows = max(1, int(len(batch) * BATCH_BYTES / max(1, batch.nbytes)))
    for a in range(0, len(batch), rows):
        yield batch.slice(a, rows)


def _encoded(model: Model, column: pa.Array) -> pa.Array:
    texts = column.to_pylist()
    ids, counts = model.encode_all([t or "" for t in texts])
    offsets = np.concatenate(([0], np.cumsum(counts))).astype(np.int32)
    nulls = column.is_null() if column.null_count else None
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(ids), mask=nulls)


def _decoded(model: Model, column: pa.Array) -> pa.Array:
    offsets = column.offsets.to_numpy()
    made = model.decode_all(column.values.to_numpy(zero_copy_only=False)[offsets[0] : offsets[-1]].astype(np.int64), offsets - offsets[0])
    return pc.if_else(column.is_valid(), made, pa.scalar(None, pa.string())) if column.null_count else made


def _mapped(df: DataFrame, model: bytes, source: str, made: dict[str, T.DataType], work: Callable[[Model, pa.Array], list[pa.Array]]) -> DataFrame:
    shared = df.sparkSession.sparkContext.broadcast(_compiled(model))  # some times the size of one vocabulary file
    kept = [c for c in df.columns if c not in made]
    schema = T.StructType([df.schema[c] for c in kept] + [T.StructField(c, kind) for c, kind in made.items()])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        compiled = shared.value
        try:
            for whole in batches:
                for batch in _slices(whole):
                    columns = work(compiled, batch.column(batch.schema.get_field_index(source)))
                    yield pa.RecordBatch.from_arrays([batch.column(batch.schema.get_field_index(c)) for c in kept] + columns, [*kept, *made])
        finally:
            compiled.forget()

    return textscan.mapped(df, run, schema)


_IDS = T.ArrayType(T.IntegerType())


def encode(df: DataFrame, model: bytes, text_col: str = "text", out: str = "ids") -> DataFrame:
    """``df`` with ``out``: the list of piece ids of each text."""
    return _mapped(df, model, text_col, {out: _IDS}, lambda m, x: [_encoded(m, x)])


def decode(df: DataFrame, model: bytes, ids_col: str = "ids", out: str = "decoded") -> DataFrame:
    """``df`` with ``out``: the text of each list of ids."""
    return _mapped(df, model, ids_col, {out: T.StringType()}, lambda m, x: [_decoded(m, x)])


def _both(model: Model, column: pa.Array) -> list[pa.Array]:
    ids = _encoded(model, column)
    return [ids, _decoded(model, ids)]


def code(df: DataFrame, model: bytes, text_col: str = "text", out: tuple[str, str] = ("ids", "decoded")) -> DataFrame:
    """``encode`` and ``decode`` of its ids in one pass."""
    return _mapped(df, model, text_col, {out[0]: _IDS, out[1]: T.StringType()}, _both)
