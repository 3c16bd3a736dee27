"""Helpers that run inside Python workers: slicing Arrow batches, words, rolling hashes, packed arrays, memory given back."""

from __future__ import annotations

import ctypes
import functools
import sys

import numpy as np
import pyarrow as pa
import xxhash
import zstandard

U64 = np.uint64
#: Odd multipliers of the mixing and rolling hashes (fixed values).
MIX_A, MIX_B, BASE_A, BASE_B = 0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53, 0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93


def worker_cache(kind: str) -> dict:
    """What this Python worker keeps for tasks of one kind, so that a model loads once; a task of another kind starts with an empty one."""
    slot = sys.__dict__.setdefault("_graphsplit_cache", {})
    if slot.get("kind") != kind:
        slot.clear()
        slot["kind"] = kind
    return slot


def give_back() -> None:
    """Return freed memory to the system: workers are reused, and what one step needed at its peak would stay with the next ones."""
    pa.default_memory_pool().release_unused()
    if sys.platform.startswith("linux"):
        ctypes.CDLL(None).malloc_trim(0)


def lean(run):
    """``run`` (batches -> batches) that gives memory back when its task ends."""

    @functools.wraps(run)
    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return wrapped


class BoundedCache(dict):
    """A dictionary that is emptied once its keys and values hold more than ``most`` bytes; long keys are not kept."""

    OVERHEAD, LONGEST = 180, 256

    def __init__(self, most: int = 32 << 20):
        super().__init__()
        self.most, self.held = most, 0

    def keep(self, items) -> None:
        for k, v in items:
            if len(k) <= self.LONGEST:
                self[k] = v
                self.held += len(k) + len(v) + self.OVERHEAD

    def tidy(self) -> None:
        if self.held > self.most:
            self.clear()
            self.held = 0


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    x = x.astype(U64, copy=True)
    x ^= x >> U64(33)
    x *= U64(MIX_A)
    x ^= x >> U64(29)
    x *= U64(MIX_B)
    x ^= x >> U64(32)
    return x


def slices(batches, columns, most_bytes: int = 4_000_000, as_lists: tuple[str, ...] | None = None):
    """From Arrow batches, the named columns of runs of rows whose texts (the last column) hold about ``most_bytes`` together.

    Columns come as lists, those that ``as_lists`` leaves out as Arrow arrays.
    """
    lists = [as_lists is None or c in as_lists for c in columns]
    for batch in batches:
        cols = [batch.column(c) for c in columns]
        text = cols[-1]
        sizes = np.asarray(pa.compute.fill_null(pa.compute.binary_length(text), 0), dtype=np.int64)
        cut = np.cumsum(sizes) // most_bytes
        edges = [0, *(np.flatnonzero(np.diff(cut)) + 1).tolist(), len(sizes)]
        for a, b in zip(edges, edges[1:], strict=False):
            if a < b:
                yield [c.slice(a, b - a).to_pylist() if as_list else c.slice(a, b - a) for c, as_list in zip(cols, lists, strict=True)]


def encoded(text: str | None) -> bytes:
    return text.encode("utf-8", "surrogatepass") if text else b""


def words_of(text: str | None) -> list[bytes]:
    """Maximal runs of bytes other than the six ASCII blanks; bytes.split() cuts at exactly these."""
    return encoded(text).split()


def word_chunks(text: str) -> list[str]:
    """``text`` cut before each single blank that stands between two characters that are no white space.

    Byte-level pre-tokenizers start a match at each such blank, so ids of the chunks, joined, are the text's ids.
    """
    parts = text.split(" ")
    out = [parts[0], *[" " + p for p in parts[1:]]]
    if all(p and not p[0].isspace() and not p[-1].isspace() for p in parts):
        return out
    joined, last = [out[0]], parts[0]
    for p, chunk in zip(parts[1:], out[1:], strict=True):
        if last and not last[-1].isspace() and p and not p[0].isspace():
            joined.append(chunk)
        else:
            joined[-1] += chunk
        last = p
    return joined


def word_codes(words: list[bytes]) -> np.ndarray:
    """Two independent 64-bit codes a word, shape (n, 2)."""
    return np.frombuffer(b"".join(map(xxhash.xxh3_128_digest, words)), dtype=U64).reshape(-1, 2)


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), dtype=U64, count=len(words))


_POWERS: dict[int, np.ndarray] = {}
#: Powers that are kept for the worker's life; longer runs are made when needed.
KEPT_POWERS = 1 << 18


def powers(base: int, n: int) -> np.ndarray:
    """base ** 0 .. base ** (n - 1) modulo 2 ** 64."""
    have = _POWERS.get(base)
    if have is None or len(have) < n:
        have = np.full(max(n, KEPT_POWERS), base, dtype=U64)
        have[0] = 1
        np.multiply.accumulate(have, out=have)
        if n <= KEPT_POWERS:
            _POWERS[base] = have
    return have[:n]


def window_hash(codes: np.ndarray, length: int, base: int) -> np.ndarray:
    """Hashes of all runs of ``length`` consecutive codes (one fewer than ``length`` at the end are left out)."""
    n = len(codes)
    if n < length:
        return np.zeros(0, dtype=U64)
    inverse = pow(base, -1, 1 << 64)
    total = np.zeros(n + 1, dtype=U64)
    np.cumsum(codes * powers(base, n), out=total[1:])
    return mix((total[length:] - total[: n - length + 1]) * powers(inverse, n - length + 1))


def pack(a: np.ndarray) -> bytes:
    """Compressed ascending integers, stored as differences."""
    a = np.asarray(a, dtype=np.int64)
    d = np.diff(a, prepend=0).astype(np.int64)
    small = d.astype(np.uint8) if len(d) and d.min() >= 0 and d.max() < 256 else d.astype(np.int32) if len(d) and abs(d).max() < 1 << 31 else d
    return bytes([small.itemsize]) + zstandard.compress(small.tobytes(), 1)


def unpack(b: bytes) -> np.ndarray:
    kind = {1: np.uint8, 4: np.int32, 8: np.int64}[b[0]]
    return np.cumsum(np.frombuffer(zstandard.decompress(b[1:]), dtype=kind).astype(np.int64))


def unpack_all(parts: list[bytes] | None) -> np.ndarray:
    """The integers of several packed arrays together, ascending, each once."""
    if not parts:
        return np.zeros(0, dtype=np.int64)
    return unpack(parts[0]) if len(parts) == 1 else np.unique(np.concatenate([unpack(p) for p in parts]))


def runs_to_spans(starts: np.ndarray, length: int) -> np.ndarray:
    """Union of [s, s + length) for ascending starts, as an (n, 2) array of disjoint spans that do not touch."""
    if not len(starts):
        return np.zeros((0, 2), dtype=np.int64)
    gap = np.flatnonzero(np.diff(starts) > length)
    return np.stack([starts[np.r_[0, gap + 1]], starts[np.r_[gap, len(starts) - 1]] + length], axis=1)
