"""Arrow-to-numpy text primitives shared by the operators that run in Python workers."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U64 = np.uint64
_PRIME = 0x100000001B3_9E5F
_INVERSE = pow(_PRIME, -1, 1 << 64)
_powers: dict[int, np.ndarray] = {}

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
IN_WORD = np.zeros(256, dtype=bool)
IN_WORD[48:58] = IN_WORD[97:123] = True
IN_WORD[128:] = True


def low_memory() -> None:
    """Arrow gives freed memory back, so that a worker's size follows the slice it works on."""
    pa.set_memory_pool(pa.system_memory_pool())


def slices(batches, column: str, limit: int = 400_000) -> Iterator[pa.RecordBatch]:
    """Runs of whole rows with about ``limit`` bytes of ``column``; one row at least, 65,536 at most."""
    for batch in batches:
        if not batch.num_rows:
            continue
        size = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
        total = np.cumsum(size.astype(np.int64))
        start = 0
        while start < len(total):
            end = max(start + 1, int(np.searchsorted(total, limit + (total[start - 1] if start else 0), "right")))
            end = min(end, start + (1 << 16))
            yield batch.slice(start, end - start)
            start = end


def raw(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of the texts, and where each begins (one more offset than texts). Null is empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if texts.null_count:
        texts = pc.fill_null(texts, "")
    wide = pa.types.is_large_string(texts.type) or pa.types.is_large_binary(texts.type)
    at = np.frombuffer(texts.buffers()[1], dtype=np.int64 if wide else np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    data = texts.buffers()[2]
    body = np.frombuffer(data, dtype=np.uint8)[at[0] : at[-1]] if data is not None else np.zeros(0, np.uint8)
    return body, at - at[0]


def powers(base: int, n: int) -> np.ndarray:
    have = _powers.get(base)
    if have is None or len(have) < n:
        have = np.full(max(n, 1 << 19), base, dtype=U64)
        have[0] = 1
        np.multiply.accumulate(have, out=have)
        if len(have) <= 1 << 22:
            _powers[base] = have
    return have[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (splitmix)."""
    x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def fold(body: np.ndarray) -> np.ndarray:
    """Lower case of ASCII and of the accented Latin letters in UTF-8."""
    low = LOWER[body]
    if len(body) > 1:
        accent = (body[:-1] == 0xC3) & (body[1:] >= 0x80) & (body[1:] <= 0x9E) & (body[1:] != 0x97)
        if accent.any():
            low[1:][accent] += 0x20
    return low


def words(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(document of each word, 64-bit hash, start, end, folded bytes).

    A word is a run of letters and digits, lower-cased; Latin-1 and general punctuation separate.
    """
    body, at = raw(texts)
    low = fold(body)
    inside = IN_WORD[low]
    if len(body) and (high := low >= 0xC2).any():
        for lead, second, width in ((0xC2, None, 2), (0xE2, 0x80, 3)):
            hit = np.flatnonzero(high & (low == lead))
            if second is not None and len(hit):
                hit = hit[(hit + 1 < len(low))]
                hit = hit[low[hit + 1] == second]
            for k in range(width):
                inside[np.minimum(hit + k, len(low) - 1)] = False
    before, after = np.zeros(len(low), bool), np.zeros(len(low), bool)
    before[1:], after[:-1] = inside[:-1], inside[1:]
    edge = at[1:-1][(at[1:-1] > 0) & (at[1:-1] < len(low))]
    before[edge], after[edge - 1] = False, False
    start, end = np.flatnonzero(inside & ~before), np.flatnonzero(inside & ~after) + 1
    total = np.zeros(len(low) + 1, U64)
    np.cumsum((low.astype(U64) + U64(1)) * powers(_PRIME, len(low)), out=total[1:])
    code = mix((total[end] - total[start]) * powers(_INVERSE, len(low) + 1)[start] + (end - start).astype(U64))
    doc = np.repeat(np.arange(len(at) - 1), np.diff(np.searchsorted(start, at)))
    return doc, code, start, end, low


def shingles(doc: np.ndarray, code: np.ndarray, n_docs: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(document, hash) of all runs of ``k`` words; a shorter document is one run of all its words."""
    count = np.bincount(doc, minlength=n_docs)
    first = np.concatenate([[0], np.cumsum(count)])[:-1]
    place = np.arange(len(doc)) - first[doc]
    total = np.zeros(len(code), U64)
    for j in range(k):
        part = code * U64((0x9E3779B97F4A7C15 * (2 * j + 1)) % (1 << 64))
        total[: len(code) - j] += part[j:]
    full = place + k <= count[doc]
    short = np.flatnonzero((count > 0) & (count < k))
    if len(short):
        add = np.zeros(n_docs, U64)
        lone = count[doc] < k
        np.add.at(add, doc[lone], mix(code[lone] + place[lone].astype(U64) * U64(0x632BE59BD9B4E019)))
        return np.concatenate([doc[full], short]), np.concatenate([mix(total[full]), mix(add[short] ^ U64(0x5851F42D4C957F2D))])
    return doc[full], mix(total[full])
