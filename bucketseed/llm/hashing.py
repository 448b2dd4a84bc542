"""Vectorised words, hashes and shingles straight from Arrow string buffers.

A word's hash is a polynomial of its bytes modulo 2^64, read off one running sum for all words of
a batch at once, then mixed. Texts are processed in slices of bounded bytes (a longer text is a
slice of its own), so memory follows the slice and not the batch.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE = 1 << 20
TEXTS = 1 << 16
BASE = np.uint64(0x9E3779B97F4A7C15)
BASE_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))

#: By byte: separators of plain words and of alphanumeric words, and A-Z lower-cased.
BYTES = np.arange(256, dtype=np.uint8)
SPACES = np.isin(BYTES, list(b"\x20\x09\x0a\x0b\x0c\x0d"))
LOWER = np.where((BYTES >= 65) & (BYTES <= 90), BYTES + 32, BYTES).astype(np.uint8)
SAME = BYTES.copy()
NOT_ALNUM = ~(((LOWER >= 97) & (LOWER <= 122)) | ((BYTES >= 48) & (BYTES <= 57)) | (BYTES >= 128))

_powers: dict[str, np.ndarray] = {"up": np.ones(1, np.uint64), "down": np.ones(1, np.uint64)}


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers["up"]) < n:
        size = max(n, SLICE)
        for name, base in (("up", BASE), ("down", BASE_INVERSE)):
            steps = np.full(size, base, np.uint64)
            steps[0] = 1
            _powers[name] = np.multiply.accumulate(steps)
    up, down = _powers["up"][:n], _powers["down"][:n]
    if n > 8 * SLICE:  # don't hold on to the powers of one very long text
        _powers.update(up=np.ones(1, np.uint64), down=np.ones(1, np.uint64))
    return up, down


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return h ^ (h >> np.uint64(32))


def pieces(batches: Iterator[pa.RecordBatch], column: str = "text") -> Iterator[tuple]:
    """(batch slice, bytes, offsets) with at most about SLICE bytes and TEXTS texts; null text is empty."""
    for batch in batches:
        col = batch.column(batch.schema.get_field_index(column))
        if col.null_count:
            col = col.fill_null("")
        col = col.cast(pa.large_string())
        n = len(col)
        if not n:
            continue
        offs = np.frombuffer(col.buffers()[1], np.int64)[col.offset : col.offset + n + 1]
        raw = col.buffers()[2]
        data = np.frombuffer(raw, np.uint8) if raw is not None and raw.size else np.zeros(0, np.uint8)
        at = 0
        while at < n:
            to = int(np.searchsorted(offs, offs[at] + SLICE, side="right")) - 1
            to = min(max(to, at + 1), at + TEXTS, n)
            yield batch.slice(at, to - at), data[offs[at] : offs[to]], offs[at : to + 1] - offs[at]
            at = to


def word_hashes(
    data: np.ndarray,
    offs: np.ndarray,
    separators: np.ndarray = SPACES,
    fold: np.ndarray = LOWER,
    beginnings: tuple[int, ...] = (),
) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words in order, and where each text's words begin (one more at the end).

    With ``beginnings``, each word is followed by its first so many bytes, where it is longer.
    """
    n = len(data)
    if not n:
        return np.zeros(0, np.uint64), np.zeros(len(offs), np.int64)
    inside = ~separators[data]
    fresh = np.zeros(n + 1, bool)
    fresh[offs] = True
    before = np.empty(n, bool)
    before[0] = True
    before[1:] = ~inside[:-1] | fresh[1:n]
    after = np.empty(n, bool)
    after[-1] = True
    after[:-1] = before[1:] | ~inside[1:]
    begin, end = np.flatnonzero(inside & before), np.flatnonzero(inside & after) + 1
    up, down = _power(n)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum((fold[data].astype(np.uint64) + np.uint64(1)) * up, out=total[1:])
    h = (total[end] - total[begin]) * down[begin]
    if not beginnings:
        return mix(h), np.searchsorted(begin, offs)
    rows = np.zeros((len(begin), 1 + len(beginnings)), np.uint64)
    there = np.ones(rows.shape, bool)
    rows[:, 0] = h
    for i, size in enumerate(beginnings, 1):
        there[:, i] = end - begin > size
        stop = np.minimum(begin + size, end)
        rows[:, i] = (total[stop] - total[begin]) * down[begin] + np.uint64(size)
    places = np.zeros(len(begin) + 1, np.int64)
    np.cumsum(there.sum(1), out=places[1:])
    return mix(rows[there]), places[np.searchsorted(begin, offs)]


def shingle_hashes(
    words: np.ndarray, first: np.ndarray, length: int = 5
) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of each text's runs of ``length`` words, repeats included; a text of fewer words is
    one shingle, a text without words has none."""
    lens = np.diff(first)
    counts = np.where(lens >= length, lens - length + 1, (lens > 0).astype(lens.dtype))
    begin = np.zeros(len(first), np.int64)
    np.cumsum(counts, out=begin[1:])
    out = np.zeros(int(begin[-1]), np.uint64)
    odd = [mix(np.array([i + 1], np.uint64))[0] | np.uint64(1) for i in range(length + 1)]
    if len(words) >= length:
        runs = words[: len(words) - length + 1] * odd[0]
        for k in range(1, length):
            runs = runs + words[k : len(words) - length + 1 + k] * odd[k]
        at = np.arange(len(runs))
        fits = at + length <= np.repeat(first[1:], lens)[: len(runs)]
        to = np.repeat(begin[:-1] - first[:-1], lens)[: len(runs)] + at
        out[to[fits]] = runs[fits]
    for n in range(1, length):
        texts = np.flatnonzero(lens == n)
        if len(texts):
            value = np.full(len(texts), n, np.uint64) * odd[length]
            for k in range(n):
                value = value + words[first[texts] + k] * odd[k]
            out[begin[texts]] = value
    return mix(out), begin


def uniques(values: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each text's distinct values, sorted within the text, and where each text's begin."""
    parts = [np.unique(values[a:b]) for a, b in zip(first[:-1], first[1:], strict=True)]
    begin = np.zeros(len(first), np.int64)
    np.cumsum([len(p) for p in parts], out=begin[1:])
    return (np.concatenate(parts) if parts else values[:0]), begin


def list_array(values: np.ndarray, first: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(first.astype(np.int32)), pa.array(values.view(np.int64)))
