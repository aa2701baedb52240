"""The two word-aligned run-length codecs and the plain bitset, on NumPy arrays.

Both codecs cut a bitmap into groups of w - 1 bits. A group of both values is a literal word. Runs of equal groups are fill
words: a flag, the value, and the run's length; the position-fill codec spends some of the length's bits on the position of
one bit by which the group before the run may differ from it.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

W = 32
GROUP = W - 1
ONES = (1 << GROUP) - 1
POSITION = 5
FILL_MOST = {"fillrun": (1 << (W - 2)) - 1, "posfill": 1 << (W - 2 - POSITION)}


@dataclass
class Runs:
    """Groups in order, as runs: value 0, ONES or a literal, for length groups."""

    value: np.ndarray
    length: np.ndarray


def runs_from_ids(ids: np.ndarray) -> Runs:
    ids = np.unique(np.asarray(ids, np.int64))
    if not len(ids):
        return Runs(np.empty(0, np.int64), np.empty(0, np.int64))
    group, bit = ids // GROUP, ids % GROUP
    at, first = np.unique(group, return_index=True)
    value = np.bitwise_or.reduceat(1 << bit, first)
    gap = np.diff(at, prepend=-1) - 1
    values = np.stack([np.zeros_like(value), value], axis=1).ravel()
    lengths = np.stack([gap, np.ones_like(gap)], axis=1).ravel()
    keep = lengths > 0
    return joined(values[keep], lengths[keep])


def joined(value: np.ndarray, length: np.ndarray) -> Runs:
    """Neighbouring runs of the same fill become one; zeros at the end are dropped."""
    if not len(value):
        return Runs(value, length)
    fill = (value == 0) | (value == ONES)
    new = np.append(True, (value[1:] != value[:-1]) | ~fill[1:])
    start = np.flatnonzero(new)
    value, length = value[start], np.add.reduceat(length, start)
    end = len(value) - (value[-1] == 0)
    return Runs(value[:end], length[:end])


def ids_from_runs(r: Runs) -> np.ndarray:
    """Runs of ones are counted out, literals by their bits; neither needs a sort, as groups come in order."""
    full, some = r.value == ONES, r.value != 0
    starts = np.cumsum(r.length) - r.length
    groups = np.where(full, r.length, 1)[some]
    row = np.repeat(np.flatnonzero(some), groups)
    group = starts[row] + np.arange(len(row)) - np.repeat(np.cumsum(groups) - groups, groups)
    which, bit = np.nonzero((r.value[row][:, None] >> np.arange(GROUP)) & 1)
    return group[which] * GROUP + bit


def encode(ids: np.ndarray, codec: str, fill_most: int | None = None) -> np.ndarray:
    """The stream of 32-bit words."""
    return words_from_runs(runs_from_ids(ids), codec, fill_most)


def words_from_runs(r: Runs, codec: str, fill_most: int | None = None) -> np.ndarray:
    """Each run gives as many words as its length needs. A literal that differs in one bit from the fill after it goes into that fill's first word."""
    most, v, k = fill_most or FILL_MOST[codec], r.value, r.length
    if not len(v):
        return np.empty(0, np.uint32)
    fill = (v == 0) | (v == ONES)
    odd = np.zeros(len(v), np.int64)  # by which bit, from 1, the run before a fill differs from it
    if codec == "posfill":
        differs = v[:-1] ^ v[1:]
        one = ~fill[:-1] & fill[1:] & (differs & (differs - 1) == 0)
        odd[1:][one] = np.bitwise_count(differs[one] - 1) + 1
    swallowed = np.append(odd[1:] > 0, False)
    first = np.where(odd > 0, np.minimum(k, most - 1), 0)  # groups of a fill that its first word counts beside the literal
    left = k - first
    parts = np.where(fill, -(-left // most), 1) * ~swallowed
    n = parts + (odd > 0)
    row = np.repeat(np.arange(len(v)), n)
    nth = np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n)
    headed = (odd[row] > 0) & (nth == 0)
    nth = nth - (odd[row] > 0)
    length = np.minimum(most, left[row] - nth * most) - (codec == "posfill")
    flag = 1 << 31 | (v[row] == ONES).astype(np.int64) << 30
    out = np.where(fill[row], flag | length, v[row])
    out = np.where(headed, flag | odd[row] << (W - 2 - POSITION) | first[row], out)
    return out.astype(np.uint32)


def decode_runs(words: np.ndarray, codec: str) -> Runs:
    """Each word gives up to two runs: the literal that a position stands for, and the fill."""
    w = words.astype(np.int64)
    fill = w >> 31 == 1
    value = np.where(w >> 30 & 1 == 1, ONES, 0)
    if codec == "fillrun":
        v, k = np.where(fill, value, w), np.where(fill, w & ((1 << 30) - 1), 1)
        return joined(v[k > 0], k[k > 0])
    p, r = np.where(fill, w >> (W - 2 - POSITION) & 31, 0), w & ((1 << (W - 2 - POSITION)) - 1)
    before = value ^ np.where(p > 0, 1 << np.maximum(p - 1, 0), 0)
    v = np.stack([before, np.where(fill, value, w)], axis=1).ravel()
    k = np.stack([(p > 0).astype(np.int64), np.where(fill, np.where(p > 0, r, r + 1), 1)], axis=1).ravel()
    return joined(v[k > 0], k[k > 0])


def decode(words: np.ndarray, codec: str) -> np.ndarray:
    return ids_from_runs(decode_runs(words, codec))


def combine(a: np.ndarray, b: np.ndarray, codec: str, op: str) -> tuple[np.ndarray, int]:
    """The operation on two streams; also the words decoded, which are all of both (for AND: up to the shorter one's end)."""
    x, y = decode_runs(a, codec), decode_runs(b, codec)
    ends = np.union1d(np.cumsum(x.length), np.cumsum(y.length))
    if not len(ends):
        return np.empty(0, np.uint32), 0
    starts = np.append(0, ends[:-1])

    def at(r: Runs) -> np.ndarray:
        which = np.searchsorted(np.cumsum(r.length), starts, side="right")
        return np.append(r.value, 0)[np.minimum(which, len(r.value))]

    value = {"and": np.bitwise_and, "or": np.bitwise_or, "xor": np.bitwise_xor}[op](at(x), at(y))
    return words_from_runs(joined(value, ends - starts), codec), len(a) + len(b)


def contains(words: np.ndarray, codec: str, x: int) -> tuple[bool, int]:
    """By reading the stream from its start; also the words read."""
    group, bit, seen = x // GROUP, x % GROUP, 0
    for i, w in enumerate(words.tolist()):
        r = decode_runs(np.array([w], np.uint32), codec) if w >> 31 else Runs(np.array([w]), np.array([1]))
        n = w & ((1 << 30) - 1) if codec == "fillrun" and w >> 31 else int(r.length.sum())
        if w >> 31 and not len(r.value):  # zeros alone
            n = (w & ((1 << 25) - 1)) + 1 if codec == "posfill" else n
        elif w >> 31 and codec == "posfill":
            n = (w & ((1 << 25) - 1)) + 1
        if group < seen + n:
            offset = group - seen
            ends = np.cumsum(r.length)
            k = int(np.searchsorted(ends, offset, side="right"))
            return k < len(r.value) and bool(int(r.value[k]) >> bit & 1), i + 1
        seen += n
    return False, len(words)


def append(words: np.ndarray, codec: str, x: int) -> np.ndarray:
    """Adds a value above all others: the last words change, or some are added."""
    tail = decode(words[-2:], codec) if len(words) else np.empty(0, np.int64)
    base = stream_groups(words[:-2], codec) * GROUP
    return np.concatenate([words[:-2], encode(np.append(tail, x - base), codec)])


def stream_groups(words: np.ndarray, codec: str) -> int:
    w = words.astype(np.int64)
    fill = w >> 31 == 1
    field = w[fill] & ((1 << (W - 2 if codec == "fillrun" else W - 2 - POSITION)) - 1)
    return int((~fill).sum() + field.sum() + (fill.sum() if codec == "posfill" else 0))


def remove(words: np.ndarray, codec: str, x: int) -> np.ndarray:
    """Rewrites the stream without x."""
    ids = decode(words, codec)
    return encode(ids[ids != x], codec)


# -- the plain bitset ------------------------------------------------------------------------------------------------


def plain_encode(ids: np.ndarray) -> np.ndarray:
    ids = np.unique(np.asarray(ids, np.int64))
    if not len(ids):
        return np.empty(0, np.uint64)
    out, at = np.zeros((int(ids[-1]) >> 6) + 1, np.uint64), ids >> 6
    first = np.flatnonzero(np.append(True, at[1:] != at[:-1]))
    out[at[first]] = np.bitwise_or.reduceat(np.uint64(1) << (ids & 63).astype(np.uint64), first)
    return out


def plain_set(words: np.ndarray, x: int) -> np.ndarray:
    """Sets a bit in the words themselves; beyond their end, in words of twice the capacity or what is needed."""
    w = x >> 6
    if w >= len(words):
        words = np.concatenate([words, np.zeros(max(w + 1, 2 * len(words)) - len(words), np.uint64)])
    words[w] |= np.uint64(1 << (x & 63))
    return words


def plain_clear(words: np.ndarray, x: int) -> np.ndarray:
    if x >> 6 < len(words):
        words[x >> 6] &= ~np.uint64(1 << (x & 63))
    return words


def plain_decode(words: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.unpackbits(words.view(np.uint8), bitorder="little"))


def plain_combine(a: np.ndarray, b: np.ndarray, op: str) -> np.ndarray:
    """On a clone of the first operand, as the operation itself overwrites."""
    n = max(len(a), len(b))
    out = np.zeros(n, np.uint64)
    out[: len(a)] = a
    if op == "and":
        out[: len(b)] &= b
        out[len(b) :] = 0
    elif op == "or":
        out[: len(b)] |= b
    else:
        out[: len(b)] ^= b
    return out


def doubling_words(ids_in_order) -> int:
    """Capacity in words after setting bits in the given order: it doubles when it must grow, or grows to what is needed, as plain_set does."""
    words = 1
    for x in ids_in_order:
        need = (int(x) >> 6) + 1
        if need > words:
            words = max(2 * words, need)
    return words
