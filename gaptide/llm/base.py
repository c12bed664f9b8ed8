"""Shared helpers: shared folders, shipping the package to workers, vectorised word hashing."""

from __future__ import annotations

import numpy as np

from ..common import attach, cut, release, shared_checkpoints, ship, stash, table

__all__ = ["attach", "cut", "release", "shared_checkpoints", "ship", "stash", "table"]
#: What operators remember in a worker process, and how each forgets it.
_kept: dict[str, object] = {}


def keep(name: str, forget) -> None:
    _kept[name] = forget


def forget_others(name: str = "") -> None:
    """Empty what other operators have kept in this worker, and give freed memory back: stages of one application share its memory."""
    import pyarrow as pa

    for other, forget in _kept.items():
        if other != name:
            forget()
    pa.default_memory_pool().release_unused()
    try:
        import ctypes

        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # not every C library can
        pass


def fresh(name: str, columns) -> str:
    """The name, with as many underscores as make it differ from all columns."""
    held = {c.lower() for c in columns}
    while name.lower() in held:
        name += "_"
    return name


#: ASCII white space that separates words: space, tab, line feed, vertical tab, form feed, return.
WORD = r"[^\x20\x09-\x0D]+"


def utf8(column) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and the n+1 offsets of an Arrow string column, without making Python strings; null is empty."""
    import pyarrow as pa

    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_string())
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64, len(column) + 1, column.offset * 8)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_rng = np.random.default_rng(20240229)
_BYTE = _rng.integers(1, 2**63, 256, dtype=np.uint64)
_R = np.uint64(0x9E3779B97F4A7C15)


def _powers(r: int, n: int) -> np.ndarray:
    out = np.full(n, r, np.uint64)
    out[0] = 1
    return np.cumprod(out, dtype=np.uint64)


_LONGEST = 64
_POWERS = _powers(int(_R), _LONGEST + 1)


def mix64(x: np.ndarray) -> np.ndarray:
    """A published 64-bit finaliser (xor-shift and multiply)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


#: Everything but ASCII letters, digits and the bytes of other letters.
NOT_ALNUM = np.ones(256, bool)
NOT_ALNUM[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = False


def words(raw: np.ndarray, offsets: np.ndarray, fold: bool = True, between: np.ndarray = _SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """64-bit hash of each word, its document's index, and its first byte. fold: A-Z count as a-z."""
    n = len(raw)
    if not n:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    low = _LOWER[raw] if fold else raw
    gap = between[raw]
    first = ~gap
    first[1:] &= gap[:-1]
    inner = offsets[:-1][(offsets[:-1] < n) & (offsets[:-1] < offsets[1:])]
    first[inner] = ~gap[inner]
    starts = np.flatnonzero(first)
    if not len(starts):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    word = np.cumsum(first) - 1
    place = np.arange(n) - starts[np.maximum(word, 0)]
    value = _BYTE[low] * _POWERS[place % _LONGEST]
    if len(place) and place.max() >= _LONGEST:  # a later block of a long word gets another multiplier
        far = place >= _LONGEST
        value[far] = mix64(value[far] + (place[far] // _LONGEST).astype(np.uint64))
    value[gap] = 0
    h = np.add.reduceat(value, starts)
    length = np.add.reduceat((~gap).astype(np.int64), starts)
    h = mix64(h + length.astype(np.uint64) * _R)
    doc = np.searchsorted(offsets, starts, side="right") - 1
    return h, doc, starts


def shingles(h: np.ndarray, doc: np.ndarray, n_docs: int, width: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the word shingles of each document and their documents; a document with fewer words has one of all its words."""
    if not len(h):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    count = np.bincount(doc, minlength=n_docs)
    begin = np.concatenate(([0], np.cumsum(count)))[:-1]
    acc = np.zeros(max(0, len(h) - width + 1), np.uint64)
    for k in range(width):
        acc = mix64(acc * _R + h[k : len(h) - width + 1 + k]) if len(acc) else acc
    whole = doc[: len(acc)] == doc[width - 1 :] if len(acc) else np.zeros(0, bool)
    out, owner = acc[whole], doc[: len(acc)][whole]
    short = np.flatnonzero((count > 0) & (count < width))
    if len(short):
        tail = []
        for d in short:
            a = count[d : d + 1].astype(np.uint64)
            for at in range(begin[d], begin[d] + count[d]):
                a = mix64(a * _R + h[at : at + 1])
            tail.append(a)
        out, owner = np.concatenate((out, *tail)), np.concatenate((owner, short))
        order = np.argsort(owner, kind="stable")
        out, owner = out[order], owner[order]
    return out, owner
