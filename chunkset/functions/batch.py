"""Operations on many containers at once: whole batches of pairs, with a fixed number of NumPy calls whatever the number of containers.

A Stack is a column of canonical containers: payloads lie in one buffer of 16-bit units, an array's values or the quarters of a bitmap's
words. Pairs are sorted by the kinds that meet, and each of the groups (bitmap and bitmap, bitmap and array, array and array by merging or by
galloping) is worked off in one go. Results are canonical, as those of the operations on single containers, which the tests compare.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa

from chunkset.functions import containers as C

UNITS = 4 * C.WORDS  # 16-bit units of a bitmap
#: Values a pair of containers from which marks beat a sort; containers that are marked at once.
MARKED, AT_ONCE = 3000, 32


@dataclass
class Stack:
    kind: np.ndarray  # int8
    card: np.ndarray  # int64
    start: np.ndarray  # first unit
    data: np.ndarray  # uint16

    def __len__(self) -> int:
        return len(self.kind)

    def take(self, rows: np.ndarray) -> Stack:
        return Stack(self.kind[rows], self.card[rows], self.start[rows], self.data)

    def units(self) -> np.ndarray:
        return np.where(self.kind == C.BITMAP, UNITS, self.card)

    def payloads(self) -> pa.Array:
        """The payloads as an Arrow column."""
        flat, size = self.flat(), self.units()
        offsets = np.append(0, np.cumsum(2 * size)).astype(np.int32)
        return pa.Array.from_buffers(pa.binary(), len(self), [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(flat))])

    def flat(self) -> np.ndarray:
        """The units of all containers in order."""
        size = self.units()
        at = np.append(0, np.cumsum(size)[:-1])
        if (np.diff(self.start) == size[:-1]).all():
            first = int(self.start[0]) if len(self) else 0
            return self.data[first : first + int(size.sum())]
        out, sparse = np.empty(int(size.sum()), np.uint16), np.flatnonzero(self.kind == C.ARRAY)
        if len(sparse):
            n = size[sparse]
            within = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
            out[np.repeat(at[sparse], n) + within] = self.data[np.repeat(self.start[sparse], n) + within]
        for a, s in zip(at[self.kind == C.BITMAP].tolist(), self.start[self.kind == C.BITMAP].tolist(), strict=True):
            out[a : a + UNITS] = self.data[s : s + UNITS]
        return out

    def values(self) -> tuple[np.ndarray, np.ndarray]:
        """Row and value of every member of arrays, as row << 16 | value, and the rows. For stacks of arrays only, of at most 65,536."""
        row = np.repeat(np.arange(len(self), dtype=np.uint32), self.card)
        return row << np.uint32(16) | self.flat(), row

    def words(self, own: bool = False) -> np.ndarray:
        """One row of 64-bit words each. For stacks of bitmaps only; a copy if own, or unless they lie in order."""
        n = len(self)
        if n and not own and (np.diff(self.start) == UNITS).all():
            part = self.data[self.start[0] : self.start[0] + n * UNITS]
            if part.ctypes.data % 8 == 0:
                return part.view(np.uint64).reshape(n, C.WORDS)
        out = np.empty((n, UNITS), np.uint16)
        for i, s in enumerate(self.start.tolist()):
            out[i] = self.data[s : s + UNITS]
        return out.view(np.uint64)


def from_column(kind: pa.Array, payload: pa.Array) -> Stack:
    """Canonical containers from Arrow columns without nulls; the payloads aren't copied."""
    offsets = np.frombuffer(payload.buffers()[1], np.int32)[payload.offset : payload.offset + len(payload) + 1].astype(np.int64)
    raw = payload.buffers()[2]
    data = np.frombuffer(raw, np.uint16, count=raw.size // 2) if raw is not None and raw.size else np.empty(0, np.uint16)
    kinds = kind.to_numpy(zero_copy_only=False)
    start, size = offsets[:-1] // 2, np.diff(offsets) // 2
    card = size.copy()
    dense = np.flatnonzero(kinds == C.BITMAP)
    if len(dense):
        card[dense] = np.bitwise_count(Stack(kinds[dense], card[dense], start[dense], data).words()).sum(1)
    return Stack(kinds, card, start, data)


def of_arrays(member: np.ndarray, rows: int) -> Stack:
    """From sorted row << 16 | value."""
    card = np.bincount(member >> 16, minlength=rows)
    return Stack(np.zeros(rows, np.int8), card, np.cumsum(card) - card, (member & 65535).astype(np.uint16))


def of_words(words: np.ndarray, card: np.ndarray) -> Stack:
    """Canonical containers from rows of words: those with few members become arrays."""
    n = len(words)
    kind = (card > C.ARRAY_MOST).astype(np.int8)
    sparse = np.flatnonzero((kind == C.ARRAY) & (card > 0))
    units = np.where(kind == C.BITMAP, UNITS, card)
    start = np.cumsum(units) - units
    if not len(sparse):
        keep = words if (kind == C.BITMAP).all() else words[kind == C.BITMAP]
        return Stack(kind, card, start, np.ascontiguousarray(keep).view(np.uint16).ravel())
    data = np.empty(int(units.sum()), np.uint16)
    picked = words if len(sparse) == n else words[sparse]
    some = np.flatnonzero(picked)  # words that aren't empty
    member = np.flatnonzero(np.unpackbits(picked.reshape(-1)[some].view(np.uint8), bitorder="little").view(bool))
    values = (some[member >> 6] << 6 | member & 63).astype(np.uint16)
    if len(sparse) == n:
        return Stack(kind, card, start, values)
    first = np.cumsum(card[sparse]) - card[sparse]
    data[np.repeat(start[sparse] - first, card[sparse]) + np.arange(len(values))] = values
    for i in np.flatnonzero(kind == C.BITMAP).tolist():
        data[start[i] : start[i] + UNITS] = words[i].view(np.uint16)
    return Stack(kind, card, start, data)


def joined(parts: list[tuple[np.ndarray, Stack]], n: int) -> Stack:
    """One stack of n rows from stacks and the rows that they stand for."""
    parts = [p for p in parts if len(p[0])]
    if len(parts) == 1 and (parts[0][0] == np.arange(n)).all():
        return parts[0][1]
    kind, card, start = np.zeros(n, np.int8), np.zeros(n, np.int64), np.zeros(n, np.int64)
    data, base = [], 0
    for rows, s in parts:
        kind[rows], card[rows], start[rows] = s.kind, s.card, s.start + base
        data.append(s.data)
        base += len(s.data)
    return Stack(kind, card, start, np.concatenate(data) if data else np.empty(0, np.uint16))


def set_words(member: np.ndarray, rows: int, words: np.ndarray | None = None) -> np.ndarray:
    """Rows of words with the bits of sorted row << 16 | value set, in words if given."""
    words = np.zeros((rows, C.WORDS), np.uint64) if words is None else words
    if len(member):
        bit = np.uint64(1) << (member & 63).astype(np.uint64)
        at = member >> 6
        first = np.flatnonzero(np.append(True, at[1:] != at[:-1]))
        words.reshape(-1)[at[first]] |= np.bitwise_or.reduceat(bit, first)
    return words


def merged(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Two sorted lists as one. The general sort is vectorised, and faster than one that looks for runs."""
    return np.sort(np.concatenate([a, b]))


def marked(x: np.ndarray, y: np.ndarray, rows: int) -> np.ndarray:
    """What two lists share, by marks for the values of one: cheaper than a sort where containers hold many values."""
    out = []
    for first in range(0, rows, AT_ONCE):
        (a, b), (c, d) = (np.searchsorted(z, [first << 16, min(first + AT_ONCE, rows) << 16]) for z in (x, y))
        flags = np.zeros(min(AT_ONCE, rows - first) << 16, bool)
        flags[x[a:b] - np.uint32(first << 16)] = True
        out.append(y[c:d][flags[y[c:d] - np.uint32(first << 16)]])
    return np.concatenate(out)


def either_words(x: np.ndarray, y: np.ndarray, rows: int) -> np.ndarray:
    """Rows of words with the bits of both lists set."""
    out = np.empty((rows, C.WORDS), np.uint64)
    for first in range(0, rows, AT_ONCE):
        n = min(AT_ONCE, rows - first)
        flags = np.zeros(n << 16, np.uint8)
        for z in (x, y):
            a, b = np.searchsorted(z, [first << 16, first + n << 16])
            flags[z[a:b] - np.uint32(first << 16)] = 1
        out[first : first + n] = np.packbits(flags, bitorder="little").view(np.uint64).reshape(n, C.WORDS)
    return out


def and_arrays(a: Stack, b: Stack, method: str = "auto") -> Stack:
    n, found = len(a), []
    short, long = np.minimum(a.card, b.card), np.maximum(a.card, b.card)
    gallop = {"auto": long >= C.GALLOP_RATIO * short, "gallop": np.ones(n, bool), "merge": np.zeros(n, bool)}[method]
    for rows, halving in ((np.flatnonzero(gallop), True), (np.flatnonzero(~gallop), False)):
        if not len(rows):
            continue
        (x, _), (y, _) = a.take(rows).values(), b.take(rows).values()
        if halving:
            x, y = (x, y) if len(x) <= len(y) else (y, x)
            both = x[y[np.minimum(np.searchsorted(y, x), len(y) - 1)] == x] if len(y) else x[:0]
        elif len(x) + len(y) >= MARKED * len(rows):
            both = marked(x, y, len(rows))
        else:
            all_ = merged(x, y)
            both = all_[:-1][all_[1:] == all_[:-1]]
        found.append((rows, of_arrays(both, len(rows))))
    return joined(found, n)


def and_bitmap_array(bitmap: Stack, array: Stack) -> Stack:
    member, row = array.values()
    low = member & 65535
    hit = bitmap.data[bitmap.start[row] + (low >> 4)] >> (low & 15).astype(np.uint16) & 1
    return of_arrays(member[hit.astype(bool)], len(array))


def or_arrays(a: Stack, b: Stack, predict: bool = True) -> Stack:
    n, found = len(a), []
    small = (a.card + b.card <= C.ARRAY_MOST) if predict else np.ones(n, bool)
    for rows, by_merge in ((np.flatnonzero(small), True), (np.flatnonzero(~small), False)):
        if not len(rows):
            continue
        x, y = a.take(rows).values()[0], b.take(rows).values()[0]
        if by_merge:
            all_ = merged(x, y)
            all_ = all_[np.append(True, all_[1:] != all_[:-1])] if len(all_) else all_
            s = of_arrays(all_, len(rows))
            if (s.card > C.ARRAY_MOST).any():  # not predicted: converted afterwards
                s = of_words(set_words(all_, len(rows)), s.card)
            found.append((rows, s))
            continue
        words = either_words(x, y, len(rows))
        found.append((rows, of_words(words, np.bitwise_count(words).sum(1, dtype=np.int64))))
    return joined(found, n)


def intersection(a: Stack, b: Stack, method: str = "auto") -> Stack:
    """Row by row. Rows may come out empty."""
    n, both = len(a), a.kind + 2 * b.kind
    found = []
    if len(rows := np.flatnonzero(both == 3)):
        words = a.take(rows).words() & b.take(rows).words()
        found.append((rows, of_words(words, np.bitwise_count(words).sum(1, dtype=np.int64))))
    if len(rows := np.flatnonzero(both == 1)):
        found.append((rows, and_bitmap_array(a.take(rows), b.take(rows))))
    if len(rows := np.flatnonzero(both == 2)):
        found.append((rows, and_bitmap_array(b.take(rows), a.take(rows))))
    if len(rows := np.flatnonzero(both == 0)):
        found.append((rows, and_arrays(a.take(rows), b.take(rows), method)))
    return joined(found, n)


def union(a: Stack, b: Stack, predict: bool = True) -> Stack:
    n, both = len(a), a.kind + 2 * b.kind
    found = []
    if len(rows := np.flatnonzero(both == 3)):
        words = a.take(rows).words() | b.take(rows).words()
        found.append((rows, of_words(words, np.bitwise_count(words).sum(1, dtype=np.int64))))
    for code, (dense, sparse) in ((1, (a, b)), (2, (b, a))):
        if len(rows := np.flatnonzero(both == code)):
            (member, row), dense = sparse.take(rows).values(), dense.take(rows)
            low = member & 65535
            old = dense.data[dense.start[row] + (low >> 4)] >> (low & 15).astype(np.uint16) & 1
            words = set_words(member, len(rows), dense.words(own=True))
            found.append((rows, of_words(words, dense.card + np.bincount(row[old == 0], minlength=len(rows)))))
    if len(rows := np.flatnonzero(both == 0)):
        found.append((rows, or_arrays(a.take(rows), b.take(rows), predict)))
    return joined(found, n)


def shared_counts(a: Stack, b: Stack) -> np.ndarray:
    """Sizes of the intersections; bitmaps are counted without being written."""
    dense = (a.kind == C.BITMAP) & (b.kind == C.BITMAP)
    out = np.zeros(len(a), np.int64)
    if dense.any():
        rows = np.flatnonzero(dense)
        out[rows] = np.bitwise_count(a.take(rows).words() & b.take(rows).words()).sum(1)
    if not dense.all():
        rows = np.flatnonzero(~dense)
        out[rows] = intersection(a.take(rows), b.take(rows)).card
    return out


@dataclass
class Packed:
    """A whole set: its keys in order, and a container for each."""

    keys: np.ndarray
    boxes: Stack

    @staticmethod
    def of(ids: np.ndarray) -> Packed:
        """From sorted, different ids."""
        ids = np.asarray(ids, np.int64)
        keys, first = np.unique(ids >> 16, return_index=True)
        card = np.diff(np.append(first, len(ids)))
        rows, dense = np.repeat(np.arange(len(keys)), card), card > C.ARRAY_MOST
        found = []
        for chosen in (~dense, dense):
            at = np.flatnonzero(chosen)
            member = ((np.cumsum(chosen) - 1)[rows] << 16 | ids & 65535)[chosen[rows]].astype(np.uint32)
            found.append((at, of_words(set_words(member, len(at)), card[at]) if chosen is dense else of_arrays(member, len(at))))
        return Packed(keys, joined(found, len(keys)))

    def ids(self) -> np.ndarray:
        out = []
        for k, kind, card, s in zip(self.keys.tolist(), self.boxes.kind.tolist(), self.boxes.card.tolist(), self.boxes.start.tolist(), strict=True):
            box = C.from_payload(kind, self.boxes.data[s : s + (UNITS if kind else card)].tobytes())
            out.append(k << 16 | C.plain_values(box).astype(np.int64))
        return np.concatenate(out) if out else np.empty(0, np.int64)


def meeting(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where the keys stand that two sorted lists share."""
    if len(a) > len(b):
        y, x = meeting(b, a)
        return x, y
    at = np.searchsorted(b, a)
    hit = np.flatnonzero(np.append(b, -1)[at] == a)
    return hit, at[hit]


def intersect_sets(a: Packed, b: Packed, method: str = "auto") -> Packed:
    i, j = meeting(a.keys, b.keys)
    out = intersection(a.boxes.take(i), b.boxes.take(j), method)
    some = np.flatnonzero(out.card)
    return Packed(a.keys[i[some]], out.take(some))


def unite_sets(a: Packed, b: Packed) -> Packed:
    i, j = meeting(a.keys, b.keys)
    both = union(a.boxes.take(i), b.boxes.take(j))
    alone_a, alone_b = np.delete(np.arange(len(a.keys)), i), np.delete(np.arange(len(b.keys)), j)
    keys = np.concatenate([a.keys[i], a.keys[alone_a], b.keys[alone_b]])
    order = np.argsort(keys, kind="stable")
    rows = np.empty(len(keys), np.int64)
    rows[order] = np.arange(len(keys))
    n = [len(i), len(alone_a), len(alone_b)]
    cut = np.cumsum([0, *n])
    lone = [packed_rows(s.boxes.take(r)) for s, r in ((a, alone_a), (b, alone_b))]
    return Packed(keys[order], joined([(rows[cut[k] : cut[k + 1]], s) for k, s in enumerate([both, *lone])], len(keys)))


def packed_rows(s: Stack) -> Stack:
    """The stack with nothing in its buffer but its own rows."""
    size = s.units()
    if size.sum() == len(s.data):
        return s
    return Stack(s.kind, s.card, np.cumsum(size) - size, s.flat())
