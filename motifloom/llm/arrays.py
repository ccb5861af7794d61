"""Word and shingle hashes of whole Arrow batches in NumPy: no Python loop per word.

A word's hash is a polynomial over per-byte random values, read off prefix sums modulo 2^64, then
mixed. Texts are worked on in slices of about SLICE bytes that end between words, so memory stays
bounded however long a text is.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

SLICE = 1 << 20
_R = np.uint64(0x9E3779B97F4A7C15)
_R_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_BYTE = np.random.default_rng(20240229).integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BYTE_LOWER = _BYTE[_LOWER]

#: True for bytes that separate words: space, tab to carriage return.
SPACES = np.zeros(256, dtype=bool)
SPACES[[0x20, *range(0x09, 0x0E)]] = True
#: True for every ASCII byte that is neither letter nor digit.
PUNCTUATION = np.ones(256, dtype=bool)
PUNCTUATION[128:] = False
for _a, _b in ((48, 58), (65, 91), (97, 123)):
    PUNCTUATION[_a:_b] = False

_powers: tuple[np.ndarray, np.ndarray] | None = None


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every input bit (public splitmix finaliser)."""
    x = x ^ (x >> np.uint64(30))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _powers
    if _powers is None or len(_powers[0]) < n:
        both = []
        for base in (_R, _R_INVERSE):
            a = np.full(n, base, dtype=np.uint64)
            a[0] = 1
            both.append(np.multiply.accumulate(a))
        _powers = (both[0], both[1])
    return _powers[0][:n], _powers[1]


def raw(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and n + 1 offsets of a binary array without nulls."""
    wide = column.cast(pa.large_binary())
    offsets = np.frombuffer(wide.buffers()[1], dtype=np.int64)[wide.offset : wide.offset + len(wide) + 1]
    data = np.frombuffer(wide.buffers()[2] or b"", dtype=np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def _cuts(data: np.ndarray, separators: np.ndarray) -> list[int]:
    """Slice borders: each at a separator or the end."""
    cuts, at, n = [0], 0, len(data)
    while n - at > SLICE:
        end, step = at + SLICE, 4096
        while end < n:
            hits = np.flatnonzero(separators[data[end : end + step]])
            if len(hits):
                end += int(hits[0])
                break
            end += step
        at = min(end, n)
        cuts.append(at)
    if cuts[-1] != n:
        cuts.append(n)
    return cuts


def words(data: np.ndarray, offsets: np.ndarray, separators: np.ndarray = SPACES, lower: bool = True, prefixes: tuple[int, ...] = ()) -> tuple[np.ndarray, ...]:
    """64-bit hashes of all words in order, and per text the index of its first word (n + 1 values).

    For each length in prefixes there follows an array of the hashes of the words' first so many
    bytes (0 for words that are not longer).
    """
    values = _BYTE_LOWER if lower else _BYTE
    hashes, starts_of = [np.empty(0, np.uint64)], [np.empty(0, np.int64)]
    heads: list[list[np.ndarray]] = [[np.empty(0, np.uint64)] for _ in prefixes]
    cuts = _cuts(data, separators)
    for a, b in zip(cuts, cuts[1:]):
        piece = data[a:b]
        inside = ~separators[piece]
        first = inside.copy()
        first[1:] &= ~inside[:-1]
        borders = offsets[np.searchsorted(offsets, a) : np.searchsorted(offsets, b)] - a
        first[borders] = inside[borders]
        last = inside.copy()
        last[:-1] &= ~inside[1:]
        ends = borders[borders > 0] - 1
        last[ends] = inside[ends]
        s, e = np.flatnonzero(first), np.flatnonzero(last) + 1
        power, inverse = _power_tables(len(piece) + 1)
        sums = np.zeros(len(piece) + 1, np.uint64)
        np.cumsum(values[piece] * power[:-1], out=sums[1:])
        hashes.append(mix((sums[e] - sums[s]) * inverse[s] + (e - s).astype(np.uint64)))
        starts_of.append(s + a)
        for k, out in zip(prefixes, heads):
            long = e - s > k
            part = np.zeros(len(s), np.uint64)
            part[long] = mix((sums[s[long] + k] - sums[s[long]]) * inverse[s[long]] + np.uint64(k << 32))
            out.append(part)
    h, at = np.concatenate(hashes), np.concatenate(starts_of)
    return h, np.searchsorted(at, offsets).astype(np.int64), *[np.concatenate(x) for x in heads]


_STEP = np.random.default_rng(20240301).integers(1, 1 << 63, 64, dtype=np.uint64) | np.uint64(1)


def grams(h: np.ndarray, first: np.ndarray, width: int, shorts: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of `width` words per text, and n + 1 offsets.

    With shorts, a text of 1 to width - 1 words gives its whole sequence as one run.
    """
    counts = np.diff(first)
    runs = np.maximum(counts - (width - 1), 0)
    full = np.zeros(max(len(h) - width + 1, 0), np.uint64)
    for k in range(width):
        full += h[k : k + len(full)] * _STEP[k]
    full = mix(full)
    lone = (counts > 0) & (counts < width) if shorts else np.zeros(len(counts), bool)
    sizes = np.where(lone, 1, runs)
    offsets = np.zeros(len(counts) + 1, np.int64)
    np.cumsum(sizes, out=offsets[1:])
    owner = np.repeat(np.arange(len(counts)), sizes)
    where = first[:-1][owner] + (np.arange(offsets[-1]) - offsets[:-1][owner])
    out = np.empty(offsets[-1], np.uint64)
    whole = runs[owner] > 0
    out[whole] = full[where[whole]]
    for i in np.flatnonzero(lone):
        run = h[first[i] : first[i + 1]]
        out[offsets[i]] = mix(np.array([(run * _STEP[: len(run)]).sum(dtype=np.uint64) + np.uint64(len(run))], np.uint64))[0]
    return out, offsets


def pairs(h: np.ndarray, first: np.ndarray, gap: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of word pairs `gap` apart, and for each the index of its text."""
    n = max(len(h) - gap, 0)
    owner = np.repeat(np.arange(len(first) - 1), np.diff(first))
    same = owner[:n] == owner[gap:]
    out = mix(h[:n] * _STEP[0] + h[gap:] * _STEP[1] + _STEP[1 + gap])
    return out[same], owner[:n][same]


def unique_per_text(values: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values of each text and their offsets; sorts text by text, within the cache."""
    v = values.copy()
    for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist()):
        v[a:b].sort()
    keep = np.ones(len(v), bool)
    keep[1:] = v[1:] != v[:-1]
    keep[offsets[:-1][np.diff(offsets) > 0]] = True
    out = np.zeros(len(offsets), np.int64)
    np.cumsum(keep, out=(total := np.zeros(len(v) + 1, np.int64))[1:])
    out[:] = total[offsets]
    return v[keep], out


def slices(batch: pa.RecordBatch, column: str, most: int = SLICE):
    """Cuts a batch into runs of rows of about `most` text bytes."""
    sizes = np.diff(raw(batch.column(batch.schema.get_field_index(column)))[1])
    start = held = 0
    for i, n in enumerate(sizes):
        if held and held + n > most:
            yield batch.slice(start, i - start)
            start, held = i, 0
        held += int(n)
    if start < len(sizes):
        yield batch.slice(start)
