"""MD5 of many short texts made of two parts, by arrays: the first 32 bits of the digests of all pairs of several groups.

One step of the digest is a few operations on arrays of words for thousands of pairs at once. Who asks for the least
digests compares these bits with a bound, and looks at the whole digest of the few pairs below it.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np

#: Pairs at a time: the words of as many stay in a processor's cache.
TILE = 1 << 15
#: Bytes of a text that fits one block.
BLOCK = 55

_SINES = [int(abs(np.sin(i + 1)) * 2**32) for i in range(64)]
_TURNS = [(7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)


def _first_words(words: list[np.ndarray | None], n: int) -> np.ndarray:
    """The first 32 bits, as the hexadecimal text has them, of the digests of n blocks; None: a word that is 0 in all of them."""
    a, b, c, d = (np.full(n, x, np.uint32) for x in _START)
    f, g = np.empty(n, np.uint32), np.empty(n, np.uint32)
    # Three steps more change the other words only.
    for i in range(61):
        if i < 16:
            at = i
            np.bitwise_xor(c, d, out=f)
            np.bitwise_and(f, b, out=f)
            np.bitwise_xor(f, d, out=f)
        elif i < 32:
            at = (5 * i + 1) % 16
            np.bitwise_xor(b, c, out=f)
            np.bitwise_and(f, d, out=f)
            np.bitwise_xor(f, c, out=f)
        elif i < 48:
            at = (3 * i + 5) % 16
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
        else:
            at = 7 * i % 16
            np.bitwise_not(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
        np.add(f, a, out=f)
        np.add(f, np.uint32(_SINES[i]), out=f)
        if words[at] is not None:
            np.add(f, words[at], out=f)
        turn = _TURNS[i // 16][i % 4]
        np.right_shift(f, np.uint32(32 - turn), out=g)
        np.left_shift(f, np.uint32(turn), out=f)
        np.bitwise_or(f, g, out=f)
        np.add(f, b, out=f)
        a, d, c, b, f = d, c, b, f, a
    return (b + np.uint32(_START[0])).byteswap()


def _placed(data: np.ndarray, starts: np.ndarray, lengths: np.ndarray, shift: int, before: bytes, after: bytes) -> np.ndarray:
    """A row of 14 words for each text: its bytes from ``shift`` on, what comes before and after them, and zeros."""
    out = np.zeros((len(starts), 56), np.uint8)
    for k in range(int(lengths.max(initial=0))):
        has = np.flatnonzero(lengths > k)
        out[has, shift + k] = data[starts[has] + k]
    rows = np.arange(len(starts))
    for k, byte in enumerate(before):
        out[:, shift - len(before) + k] = byte
    for k, byte in enumerate(after):
        out[rows, shift + lengths + k] = byte
    return out.view("<u4")


def below(left: tuple[np.ndarray, np.ndarray], right: tuple[np.ndarray, np.ndarray], groups: tuple[np.ndarray, np.ndarray], bound: int, sep: bytes = b"|") -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Numbers of the left and right texts whose joint text left + sep + right has a digest with first 32 bits up to the bound.

    left, right: bytes, and where in them texts begin and the last one ends. groups: for either side, where in its texts
    groups begin and the last one ends; texts of one group are paired.
    """
    (ldata, lat), (rdata, rat), (lgroups, rgroups) = left, right, groups
    llen, rlen = np.diff(lat), np.diff(rat)
    # For each left text, where its partners begin and how many they are.
    own = np.repeat(np.arange(len(lgroups) - 1), np.diff(lgroups))
    first, many = rgroups[own], np.diff(rgroups)[own]
    most = int(rlen.max(initial=0))
    for size in np.unique(llen):
        chosen = np.flatnonzero((llen == size) & (many > 0))
        if not len(chosen):
            continue
        shift = int(size) + len(sep)
        fit = np.flatnonzero(shift + rlen <= BLOCK)
        if shift + most > BLOCK:
            yield from _long(left, right, chosen, first, many, bound, sep, shift)
        if not len(fit):
            continue
        x = _placed(ldata, lat[:-1][chosen], llen[chosen], 0, b"", sep) if shift <= 56 else None
        y = np.zeros((len(rlen), 14), np.uint32)
        y[fit] = _placed(rdata, rat[:-1][fit], rlen[fit], shift, b"", b"\x80")
        bits = ((shift + rlen) * 8).astype(np.uint32)
        used = [k for k in range(14) if 4 * k <= min(BLOCK, shift + most)]
        xs, ys = {k: np.ascontiguousarray(x[:, k]) for k in used}, {k: np.ascontiguousarray(y[:, k]) for k in used}
        ends = np.cumsum(many[chosen])
        at = 0
        while at < len(chosen):
            done = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, done + TILE, side="right")))
            i = np.repeat(np.arange(at, to), many[chosen[at:to]])
            j = first[chosen[i]] + np.arange(done, ends[to - 1]) - np.repeat(ends[at:to] - many[chosen[at:to]], many[chosen[at:to]])
            if shift + most > BLOCK:
                short = shift + rlen[j] <= BLOCK
                i, j = i[short], j[short]
            words: list[np.ndarray | None] = [None] * 16
            for k in used:
                words[k] = xs[k][i] if 4 * k + 4 <= shift else ys[k][j] if 4 * k >= shift else xs[k][i] | ys[k][j]
            words[14] = bits[j]
            hit = np.flatnonzero(_first_words(words, len(j)) <= bound)
            if len(hit):
                yield chosen[i[hit]], j[hit]
            at = to


def _long(left, right, chosen, first, many, bound, sep, shift) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs whose text takes more than a block, one by one."""
    (ldata, lat), (rdata, rat) = left, right
    found = []
    for i in chosen:
        start = hashlib.md5(ldata[lat[i] : lat[i + 1]].tobytes() + sep, usedforsecurity=False)
        for j in range(first[i], first[i] + many[i]):
            if shift + rat[j + 1] - rat[j] > BLOCK:
                whole = start.copy()
                whole.update(rdata[rat[j] : rat[j + 1]].tobytes())
                if int.from_bytes(whole.digest()[:4], "big") <= bound:
                    found.append((i, j))
    if found:
        yield tuple(np.array(found).T)
