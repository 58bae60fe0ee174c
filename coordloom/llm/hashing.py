"""Words and shingles of whole Arrow batches as 64-bit hashes, in numpy without an object per word.

A word's bytes are taken eight at a time into a chain of bijective mixes that starts from its length, so words of up to
eight bytes and one length never collide, and no pattern in longer ones cancels out (as it does in polynomials
modulo 2**64); words of over ``CHAIN_BYTES`` are hashed by blake2. Equal byte strings have equal hashes wherever they stand.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np

U = np.uint64
#: Bytes of text that are worked on at a time; a longer text is a slice of its own.
SLICE_BYTES = 1 << 21
_BASE = 0x9E3779B97F4A7C15
_rng = np.random.default_rng(20240229)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[32, *range(9, 14)]] = True
#: Longer words go through blake2 one by one.
CHAIN_BYTES = 256
_BYTES_OF = np.array([(1 << (8 * k)) - 1 for k in range(9)], dtype=np.uint64)
MULTIPLIERS = _rng.integers(1, 1 << 63, 64, dtype=np.uint64) * U(2) + U(1)
_powers: dict[str, np.ndarray] = {}


def _power_table(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, grown by need and kept within one worker."""
    if len(_powers.get("up", ())) < n:
        size = max(n, SLICE_BYTES + 1)
        for name, base in (("up", _BASE), ("down", pow(_BASE, -1, 1 << 64))):
            table = np.full(size, base, dtype=np.uint64)
            table[0] = 1
            _powers[name] = np.cumprod(table, dtype=np.uint64)
    return _powers["up"], _powers["down"]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on uint64."""
    x = x ^ (x >> U(33))
    x = x * U(0xFF51AFD7ED558CCD)
    x = x ^ (x >> U(33))
    x = x * U(0xC4CEB9FE1A85EC53)
    return x ^ (x >> U(33))


def slices(batch, column: int = 1, limit: int = SLICE_BYTES) -> Iterator:
    """Parts of a record batch of about ``limit`` bytes of text."""
    if not batch.num_rows:
        return
    import pyarrow.compute as pc

    sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(column)), 0), dtype=np.int64)
    part = np.cumsum(sizes) // limit
    cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), batch.num_rows]
    for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
        if hi > lo:
            yield batch.slice(lo, hi - lo)


def word_spans(texts, lower: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(bytes, start and stop of each word, first word of each text and the total) of a string array; null is empty."""
    import pyarrow as pa

    texts = texts.cast(pa.large_binary())
    texts = pa.concat_arrays([texts]) if texts.offset == 0 else pa.array(texts.to_pylist(), pa.large_binary())
    n = len(texts)
    offsets = np.frombuffer(texts.buffers()[1], dtype=np.int64, count=n + 1)
    data = np.frombuffer(texts.buffers()[2], dtype=np.uint8)[offsets[0] : offsets[-1]] if texts.buffers()[2] is not None and offsets[-1] > offsets[0] else np.empty(0, np.uint8)
    offsets = offsets - offsets[0]
    if lower:
        data = _LOWER[data]
    inside = ~_SPACE[data]
    first = np.zeros(len(data) + 1, dtype=bool)
    first[offsets] = True
    starts = np.flatnonzero(inside & (first[:-1] | np.concatenate(([True], ~inside[:-1])))) if len(data) else np.empty(0, np.int64)
    stops = np.flatnonzero(inside & (first[1:] | np.concatenate((~inside[1:], [True])))) + 1 if len(data) else np.empty(0, np.int64)
    return data, starts, stops, np.searchsorted(starts, offsets)


def _chained(data: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
    sizes = stops - starts
    out = mix(sizes.astype(np.uint64) * MULTIPLIERS[20] + MULTIPLIERS[21])
    padded = np.concatenate((data, np.zeros(8, np.uint8)))
    eight = np.ndarray((len(data) + 1,), dtype=np.uint64, buffer=padded.data, strides=(1,))  # the eight bytes from each place on
    live = np.flatnonzero(sizes <= CHAIN_BYTES)
    done = 0
    while len(live):
        chunk = eight[starts[live] + done] & _BYTES_OF[np.minimum(sizes[live] - done, 8)]
        out[live] = mix(out[live] ^ chunk)
        done += 8
        live = live[sizes[live] > done]
    for k in np.flatnonzero(sizes > CHAIN_BYTES).tolist():
        out[k] = int.from_bytes(hashlib.blake2b(data[starts[k] : stops[k]].tobytes(), digest_size=8).digest(), "little")
    return out


def word_hashes(texts, lower: bool) -> tuple[np.ndarray, np.ndarray]:
    """(hash of each word, bounds of each text's words)."""
    data, starts, stops, bounds = word_spans(texts, lower)
    return (_chained(data, starts, stops) if len(starts) else np.empty(0, np.uint64)), bounds


def spans_of(words: np.ndarray, width: int) -> np.ndarray:
    """Hash of every run of ``width`` words in the flat array, over the ends of texts too: the caller drops those."""
    n = len(words) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    if width <= 8:
        total = np.zeros(n, dtype=np.uint64)
        for k in range(width):
            total += words[k : k + n] * MULTIPLIERS[k]
        return mix(total)
    # the words are mixed already: a sum over powers of an odd base, from prefix sums
    up, down = _power_table(len(words) + 1)
    sums = np.zeros(len(words) + 1, dtype=np.uint64)
    np.cumsum(words * up[: len(words)], dtype=np.uint64, out=sums[1:])
    return mix((sums[width:] - sums[:-width]) * down[:n])


def shingle_sets(words: np.ndarray, bounds: np.ndarray, width: int) -> list[np.ndarray]:
    """Sorted distinct shingles of each text; a shorter text is one shingle of its own length, an empty one has none."""
    all_spans, out = spans_of(words, width), []
    for lo, hi in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        if hi - lo >= width:
            out.append(np.unique(all_spans[lo : hi - width + 1]))
        elif hi > lo:
            short = (words[lo:hi] * MULTIPLIERS[: hi - lo]).sum(dtype=np.uint64, keepdims=True)
            out.append(mix(short + MULTIPLIERS[32 + hi - lo]))
        else:
            out.append(np.empty(0, np.uint64))
    return out
