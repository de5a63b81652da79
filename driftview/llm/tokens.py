"""Vectorized tokens: whole Arrow string buffers become arrays of word hashes.

A word is a maximal run of bytes for which a 256-entry table holds true, so a
class of characters that holds all or no code points from U+0080 on is exact on
UTF-8.  Texts are read in blocks, which bounds memory for texts of any length.
"""

from __future__ import annotations

import ctypes
import functools
import gc
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa

BLOCK = 1 << 18
_MULT = np.uint64(0x9E3779B97F4A7C15)
_C1 = np.uint64(0xBF58476D1CE4E5B9)
_C2 = np.uint64(0x94D049BB133111EB)
_BASE = 0xD6E8FEB86659FD93


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit words."""
    with np.errstate(over="ignore"):
        x = x + _MULT
        x = (x ^ (x >> np.uint64(30))) * _C1
        x = (x ^ (x >> np.uint64(27))) * _C2
        return x ^ (x >> np.uint64(31))


def uniform(x: np.ndarray) -> np.ndarray:
    """Doubles in (0, 1) from scrambled words."""
    return ((x >> np.uint64(11)).astype(np.float64) + 0.5) * (1.0 / (1 << 53))


def _powers(n: int, base: int) -> np.ndarray:
    out = np.ones(n, np.uint64)
    with np.errstate(over="ignore"):
        out[1:] = np.uint64(base)
        return np.multiply.accumulate(out)


class _Powers:
    """Powers of an odd base and of its inverse modulo 2**64, grown on demand."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, np.uint64)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            n = max(n, BLOCK + 4096)
            self.up, self.down = _powers(n, _BASE), _powers(n, pow(_BASE, -1, 1 << 64))
        return self.up, self.down


_POWERS = _Powers()
_VALUE = mix(np.arange(1, 257, dtype=np.uint64))


def give_back() -> None:
    """Return freed memory to the system: a Python worker that waits for its next task holds on to it otherwise."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


Batches = Iterator[pa.RecordBatch]


def frugal(run: Callable[[Batches], Batches]) -> Callable[[Batches], Batches]:
    """``run``, for mapInArrow, which gives back its memory at the end of a partition."""

    @functools.wraps(run)
    def whole(batches: Batches) -> Batches:
        try:
            yield from run(batches)
        finally:
            give_back()

    return whole


def byte_class(keep) -> np.ndarray:
    return np.array([bool(keep(b)) for b in range(256)])


#: Letters and digits of ASCII, and everything from U+0080 on.
WORD = byte_class(lambda b: b >= 0x80 or chr(b).isalnum())
#: Everything but white space of ASCII.
GRAPH = byte_class(lambda b: not (b == 0x20 or 9 <= b <= 13))
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] += 32


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and the offsets of its texts; null is empty."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_string())
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    return (np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)), offsets


class Tokens:
    """Words of several texts: a hash each, and where each text's words begin."""

    def __init__(self, hashes: np.ndarray, starts: np.ndarray, tails: np.ndarray | None = None) -> None:
        self.hashes, self.starts, self.tails = hashes, starts, tails

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.starts)

    def owners(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.starts) - 1), self.counts)


def _block_words(piece: np.ndarray, keep: np.ndarray, breaks: np.ndarray, heads: tuple[int, ...]) -> tuple:
    """Start and hash of each word of a block; ``breaks``: offsets at which a text begins."""
    mask = keep[piece]
    before = np.empty_like(mask)
    before[0], before[1:] = False, mask[:-1]
    before[breaks] = False
    starts = np.flatnonzero(mask & ~before)
    after = np.empty_like(mask)
    after[-1], after[:-1] = False, mask[1:]
    inner = breaks[breaks > 0] - 1
    after[inner] = False
    ends = np.flatnonzero(mask & ~after) + 1
    up, down = _POWERS.upto(len(piece) + 1)
    with np.errstate(over="ignore"):
        sums = np.empty(len(piece) + 1, np.uint64)
        sums[0] = 0
        np.add.accumulate(_VALUE[piece] * up[: len(piece)], out=sums[1:])
        hashes = mix((sums[ends] - sums[starts]) * down[starts])
        parts = [mix((sums[np.minimum(ends, starts + n)] - sums[starts]) * down[starts] + np.uint64(n)) for n in heads]
    last = piece[ends - 1].astype(np.uint16)
    tails = last | (np.where(ends - starts > 1, piece[np.maximum(ends - 2, 0)], 0).astype(np.uint16) << np.uint16(8))
    return starts, hashes, tails, parts


def words(column: pa.Array, keep: np.ndarray = WORD, fold: bool = True, heads: tuple[int, ...] = ()) -> Tokens:
    """Tokens of a string column.

    ``fold`` lower-cases A-Z.  ``heads`` asks for hashes of the first so many
    bytes of each word as well, in ``Tokens.heads``.  ``tails`` holds the last
    two bytes of each word.
    """
    data, offsets = utf8(column)
    out, firsts, tails, parts = [], [], [], [[] for _ in heads]
    at, end = int(offsets[0]), int(offsets[-1])
    while at < end:
        stop = min(end, at + BLOCK)
        if stop < end:  # not inside a word: back to the last byte outside one, else on to the next
            back = np.flatnonzero(~keep[data[at:stop]])
            if len(back):
                stop = at + int(back[-1]) + 1
            else:
                while stop < end and keep[data[stop]]:
                    stop += 1
        piece = data[at:stop]
        if fold:
            piece = _FOLD[piece]
        lo, hi = np.searchsorted(offsets, [at, stop])
        breaks = np.unique(offsets[lo:hi] - at)
        breaks = breaks[breaks < len(piece)]
        starts, hashes, tail, more = _block_words(piece, keep, breaks, heads)
        firsts.append(starts + at)
        out.append(hashes)
        tails.append(tail)
        for k, x in enumerate(more):
            parts[k].append(x)
        at = stop
    cat = lambda xs, kind: np.concatenate(xs) if xs else np.zeros(0, kind)
    first = cat(firsts, np.int64)
    found = Tokens(cat(out, np.uint64), np.searchsorted(first, offsets), cat(tails, np.uint16))
    found.heads = [cat(x, np.uint64) for x in parts]
    return found


def slices(batch: pa.RecordBatch, text: str, limit: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Consecutive rows of about ``limit`` bytes of text at most, one row at least."""
    if not batch.num_rows:
        return
    _, offsets = utf8(batch.column(text))
    sizes = offsets - offsets[0]
    at = 0
    while at < batch.num_rows:
        stop = max(at + 1, int(np.searchsorted(sizes, sizes[at] + limit, "right")) - 1)
        yield batch.slice(at, stop - at)
        at = stop


def within(batches: Iterator[pa.RecordBatch], text: str, room: int, limit: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Slices of the batches up to the first text that does not fit into ``room`` bytes; batches after it are read, and dropped."""
    for batch in batches:
        for part in slices(batch, text, limit):
            ends = np.diff(utf8(part.column(text))[1]).cumsum()
            n = int(np.searchsorted(ends, room, "right")) if room >= 0 else 0
            if n:
                yield part.slice(0, n)
            room = room - int(ends[-1]) if n == len(ends) else -1


def shingles(tokens: Tokens, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Owner and hash of every run of ``width`` words; a shorter text that has words is one run."""
    h, counts = tokens.hashes, tokens.counts
    owners = tokens.owners()
    with np.errstate(over="ignore"):
        n = max(0, len(h) - width + 1)
        acc = np.zeros(n, np.uint64)
        for k in range(width):
            acc = acc * np.uint64(0x100000001B3) + h[k : k + n]
        whole = owners[:n] == owners[width - 1 :] if n else np.zeros(0, bool)
        who, what = owners[:n][whole], mix(acc[whole])
        short = np.flatnonzero((counts > 0) & (counts < width))
        if len(short):
            extra = np.array([_fold(h[tokens.starts[i] : tokens.starts[i + 1]]) for i in short], np.uint64)
            who, what = np.concatenate([who, short]), np.concatenate([what, mix(extra)])
            order = np.argsort(who, kind="stable")
            who, what = who[order], what[order]
    return who, what


def _fold(h: np.ndarray) -> int:
    acc = 0x51ED270B
    for x in h.tolist():
        acc = (acc * 0x100000001B3 + x) & 0xFFFFFFFFFFFFFFFF
    return acc


def distinct(who: np.ndarray, what: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (owner, value) pairs in order, and how often each occurs; ``who`` is ascending."""
    if not len(who):
        return who, what, np.zeros(0, np.int64)
    order = np.lexsort((what, who))
    who, what = who[order], what[order]
    new = np.empty(len(who), bool)
    new[0] = True
    new[1:] = (who[1:] != who[:-1]) | (what[1:] != what[:-1])
    at = np.flatnonzero(new)
    return who[at], what[at], np.diff(np.append(at, len(who)))


def text_digests(tokens: Tokens) -> tuple[np.ndarray, np.ndarray]:
    """128 bits of each text's word sequence."""
    with np.errstate(over="ignore"):
        at = np.arange(len(tokens.hashes), dtype=np.uint64) - np.repeat(tokens.starts[:-1], tokens.counts).astype(np.uint64)
        outs = []
        for seed in (1, 2):
            v = mix(tokens.hashes ^ mix(at * np.uint64(2) + np.uint64(seed)))
            sums = np.zeros(len(v) + 1, np.uint64)
            np.add.accumulate(v, out=sums[1:])
            outs.append(mix(sums[tokens.starts[1:]] - sums[tokens.starts[:-1]] + tokens.counts.astype(np.uint64)))
    return outs[0], outs[1]
