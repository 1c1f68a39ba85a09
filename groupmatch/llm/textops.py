"""Words of whole texts as 64-bit hashes, computed with array operations on UTF-8 bytes."""

from __future__ import annotations

import re

import numpy as np

#: A word is a run without space, tab, line feed, vertical tab, form feed or carriage return.
WORD = r"[^\x20\x09-\x0D]+"
#: Bytes of text that are hashed together; small enough for a processor's cache.
PIECE = 1 << 18
_U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_BREAK = re.compile(rb"[\x20\x09-\x0D]")
_IS_BREAK = np.zeros(256, bool)
_IS_BREAK[[0x20, *range(0x09, 0x0E)]] = True
LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_powers: list[np.ndarray] = []


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit values (splitmix)."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def distinct(x: np.ndarray) -> np.ndarray:
    """Sorted distinct values (by sorting, which is vectorised)."""
    x = np.sort(x)
    return x[np.concatenate(([True], x[1:] != x[:-1]))] if len(x) else x


def _tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _powers or len(_powers[0]) < n:
        size = max(n, PIECE + 4096)
        inverse = pow(_BASE, -1, 1 << 64)
        out = []
        for base in (_BASE, inverse):
            a = np.full(size, base, np.uint64)
            a[0] = 1
            out.append(np.multiply.accumulate(a))
        _powers[:] = out
    return _powers[0], _powers[1]


def word_spans(buffer: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Start and end of each word of one buffer."""
    gap = _IS_BREAK[np.frombuffer(buffer, np.uint8)]
    edges = np.flatnonzero(np.diff(np.concatenate(([True], gap, [True]))))
    return edges[0::2], edges[1::2]


def hash_words(buffer: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, start and end of each word; equal words have equal hashes wherever they stand."""
    starts, ends = word_spans(buffer)
    if not len(starts):
        return np.zeros(0, np.uint64), starts, ends
    up, down = _tables(len(buffer) + 1)
    sums = np.zeros(len(buffer) + 1, np.uint64)
    np.cumsum((np.frombuffer(buffer, np.uint8).astype(np.uint64) + _U(1)) * up[: len(buffer)], out=sums[1:])
    body = (sums[ends] - sums[starts]) * down[starts]
    return mix(body + mix((ends - starts).astype(np.uint64))), starts, ends


def pieces(text: bytes):
    """A long text cut before white space, so that no word is split; memory stays bounded."""
    at = 0
    while len(text) - at > PIECE:
        found = _BREAK.search(text, at + PIECE)
        if found is None:
            break
        yield text[at : found.start()]
        at = found.start()
    yield text[at:]


def batches(texts, limit: int = PIECE):
    """Indexes of `texts` (bytes) in groups of about `limit` bytes."""
    group, size = [], 0
    for i, t in enumerate(texts):
        if group and size + len(t) > limit:
            yield group
            group, size = [], 0
        group.append(i)
        size += len(t) + 1
    if group:
        yield group


def words_by_text(texts: list[bytes]):
    """Yields (index, word hashes) for every text, in order."""
    for group in batches(texts):
        if len(group) == 1 and len(texts[group[0]]) > PIECE:
            parts = [hash_words(p)[0] for p in pieces(texts[group[0]])]
            yield group[0], np.concatenate(parts)
            continue
        joined = b"\n".join(texts[i] for i in group)
        hashes, starts, _ = hash_words(joined)
        bounds = np.cumsum([0] + [len(texts[i]) + 1 for i in group])
        cuts = np.searchsorted(starts, bounds)
        for k, i in enumerate(group):
            yield i, hashes[cuts[k] : cuts[k + 1]]


def windows(hashes: np.ndarray, n: int) -> np.ndarray:
    """Hash of each run of `n` words; none if there are fewer."""
    if len(hashes) < n:
        return np.zeros(0, np.uint64)
    out = np.zeros(len(hashes) - n + 1, np.uint64)
    for k in range(n):
        out = out * _U(0xD6E8FEB86659FD93) + hashes[k : k + len(out)]
    return mix(out)


def take_spans(raw: np.ndarray, begin: np.ndarray, length: np.ndarray) -> np.ndarray:
    """The spans' values, one after another."""
    total = int(length.sum())
    shift = np.repeat(begin - np.concatenate(([0], np.cumsum(length)))[:-1], length)
    return raw[np.arange(total) + shift]


def utf8(column) -> list[bytes]:
    """Texts of an Arrow string column as bytes; null is empty."""
    import pyarrow as pa

    return [b"" if x is None else x for x in column.cast(pa.binary()).to_pylist()]


def sliced(batch, column: int, limit: int = 4 << 20):
    """Parts of an Arrow batch with about `limit` bytes of a string column each, or one longer row."""
    import pyarrow.compute as pc

    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64) + 64)
    at = 0
    while at < batch.num_rows:
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + limit, "right")))
        yield batch.slice(at, to - at)
        at = to


def trimmed(run):
    """A task's function that gives freed memory back at its end; worker processes outlive their tasks."""

    def task(it):
        yield from run(it)
        del it
        give_back()

    return task


def give_back() -> None:
    """Return freed memory of this process to the system."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)
