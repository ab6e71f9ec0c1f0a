"""Words, shingles and sketches of whole Arrow text columns as numpy arrays.

A word is a run of bytes other than 0x20 and 0x09-0x0D after lower-casing A-Z.  The words of a
block are told apart by their bytes, and each distinct one has a BLAKE2 digest.  Features of
classifiers, where two words may share a value, have a quicker polynomial over their bytes,
taken from running sums so that all words of a block are hashed at once.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa

BLOCK = 1 << 19  # bytes hashed at once; a longer word makes its block longer
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, 9, 10, 11, 12, 13]] = True
_powers: list[np.ndarray] = []


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers whose output bits depend on all input bits."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x = x * np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2**64, at least n of them."""
    if not _powers or len(_powers[0]) < n:
        inverse = np.uint64(pow(int(_BASE), -1, 1 << 64))
        _powers[:] = [np.concatenate([[np.uint64(1)], np.cumprod(np.full(n, b, dtype=np.uint64))]) for b in (_BASE, inverse)]
    return _powers[0], _powers[1]


def trim() -> None:
    """Returns freed memory to the system."""
    pa.default_memory_pool().release_unused()
    free = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of the GNU library only
    if free is not None:
        free(0)


def give_back() -> None:
    """Returns what is free to the system: the driver's Python and the workers live on beside a JVM."""
    _powers.clear()  # made again when they are needed
    gc.collect()
    trim()


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; a null has no bytes."""
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], type=pa.string())
    if len(column) == 0:
        return np.zeros(0, dtype=np.uint8), np.zeros(1, dtype=np.int64)
    if column.null_count:
        column = column.fill_null("")
    if not pa.types.is_large_string(column.type):
        column = column.cast(pa.large_string())
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, dtype=np.uint8)[at[0] : at[-1]] if data is not None else np.zeros(0, dtype=np.uint8)
    return raw, at - at[0]


def _cuts(raw: np.ndarray, offsets: np.ndarray, most: int) -> list[int]:
    """Ends of blocks: at a document's start or at white space, so that no word is cut."""
    cuts, at = [], 0
    while len(raw) - at > most:
        end = at + most
        k = np.searchsorted(offsets, end, side="right") - 1
        if offsets[k] > at:
            end = int(offsets[k])
        else:
            back = np.flatnonzero(SPACE[raw[at:end]])
            if len(back):
                end = at + int(back[-1]) + 1
            else:
                limit = int(offsets[k + 1])
                while end < limit:
                    ahead = np.flatnonzero(SPACE[raw[end : min(end + most, limit)]])
                    if len(ahead):
                        end += int(ahead[0]) + 1
                        break
                    end = min(end + most, limit)
        cuts.append(end)
        at = end
    if at < len(raw):
        cuts.append(len(raw))
    return cuts


def blocks(raw: np.ndarray, offsets: np.ndarray, most: int = BLOCK) -> Iterator[tuple[int, int]]:
    """(begin, end) of consecutive parts that cut no word."""
    at = 0
    for end in _cuts(raw, offsets, most):
        yield at, end
        at = end


def word_spans(raw: np.ndarray, offsets: np.ndarray, breaks: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(starts, ends) of the words of one block; breaks: bytes that are no part of a word."""
    part = ~(SPACE if breaks is None else breaks)[raw]
    starts = part.copy()
    starts[1:] &= ~part[:-1]
    ends = part.copy()
    ends[:-1] &= ~part[1:]
    inside = offsets[(offsets > 0) & (offsets < len(raw))]
    starts[inside] = part[inside]
    ends[inside - 1] = part[inside - 1]
    return np.flatnonzero(starts), np.flatnonzero(ends) + 1


def span_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    power, inverse = _tables(max(len(raw), BLOCK))
    total = np.zeros(len(raw) + 1, dtype=np.uint64)
    np.cumsum((LOWER[raw].astype(np.uint64) + np.uint64(1)) * power[: len(raw)], out=total[1:])
    return mix((total[ends] - total[starts]) * inverse[starts] + (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


def distinct_words(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, list[bytes]]:
    """(number of each word's bytes in the list, the distinct words); the spans hold all of ``raw`` but its white space."""
    at = np.concatenate([[0], np.cumsum(ends - starts)]).astype(np.int64)
    buffers = [None, pa.py_buffer(at), pa.py_buffer(raw[~SPACE[raw]])]
    found = pa.Array.from_buffers(pa.large_binary(), len(starts), buffers).dictionary_encode()
    return found.indices.to_numpy(), found.dictionary.to_pylist()


def word_hashes(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(64-bit digest of every word, number of words of every document), in order."""
    found, counts = [], np.zeros(len(offsets) - 1, dtype=np.int64)
    for at, end in blocks(raw, offsets, 2 * BLOCK):
        block = LOWER[raw[at:end]]
        starts, ends = word_spans(block, offsets - at)
        code, words = distinct_words(block, starts, ends)
        digests = np.frombuffer(b"".join([blake2b(w, digest_size=8).digest() for w in words]), dtype="<u8")
        found.append(digests[code])
        doc = np.searchsorted(offsets, starts + at, side="right") - 1
        counts += np.bincount(doc, minlength=len(counts))
    return (np.concatenate(found) if found else np.zeros(0, dtype=np.uint64)), counts


def shingle_sets(raw: np.ndarray, offsets: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(sorted distinct shingle hashes of each document one after the other, set sizes).

    A shingle's hash mixes in its words' digests one after the other.  A document of fewer
    than ``width`` words, but some, has one shingle: its whole sequence.
    """
    words, counts = word_hashes(raw, offsets)
    first = np.concatenate([[0], np.cumsum(counts)])
    step = np.uint64(0x9FB21C651E98DF25)
    whole = np.full(max(0, len(words) - width + 1), width, dtype=np.uint64)
    for k in range(width):
        whole = mix(whole * step + words[k : k + len(whole)])
    sets, sizes = [], np.zeros(len(counts), dtype=np.int64)
    for i, n in enumerate(counts):
        if n >= width:
            own = np.unique(whole[first[i] : first[i] + n - width + 1])
        elif n:
            own = np.array([n], dtype=np.uint64)
            for word in words[first[i] : first[i] + n]:
                own = mix(own * step + word)
        else:
            continue
        sets.append(own)
        sizes[i] = len(own)
    return (np.concatenate(sets) if sets else np.zeros(0, dtype=np.uint64)), sizes


def set_digests(flat: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit digests of each set that do not depend on its order."""
    out = []
    ends = np.cumsum(sizes)
    for seed in (0x1234567, 0x7654321):
        total = np.concatenate([[np.uint64(0)], np.cumsum(mix(flat + np.uint64(seed) * np.uint64(0x9E3779B97F4A7C15)))])
        out.append((total[ends] - total[ends - sizes]).view(np.int64))
    return out[0], out[1]


def similarity_sketch(flat: np.ndarray, sizes: np.ndarray, t: int, seed: int = 1) -> np.ndarray:
    """(documents, t) coordinates that agree between two sets with the probability of their Jaccard similarity.

    Round r throws every element into a hashed bin; a bin keeps the least value of the
    first round that reached it.  From round t on, round r throws all elements into bin
    r - t, so that every bin is filled after 2 t rounds at the latest; a document leaves as
    soon as its bins are full.  An empty set keeps the largest value everywhere.
    """
    docs = len(sizes)
    out = np.full(docs * t, np.iinfo(np.uint64).max, dtype=np.uint64)
    doc = np.repeat(np.arange(docs, dtype=np.int64), sizes)
    item = flat
    open_bins = np.where(sizes > 0, t, 0)
    for r in range(2 * t):
        if not len(item):
            break
        h = mix(item ^ np.uint64((seed * 0x9E3779B97F4A7C15 + r * 0xD1B54A32D192ED03) % 2**64))
        if r < t:
            at = doc * t + ((h >> np.uint64(32)) * np.uint64(t) >> np.uint64(32)).astype(np.int64)
        else:
            at = doc * t + (r - t)
        # the value holds its round in the upper bits: equal values mean the same element in the same round
        value = (np.uint64(r) << np.uint64(48)) | (mix(h) >> np.uint64(16))
        free = (out[at] >> np.uint64(48)) >= np.uint64(r)
        at, value = at[free], value[free]
        if len(at):
            fresh = np.unique(at[out[at] == np.iinfo(np.uint64).max])
            np.minimum.at(out, at, value)
            open_bins -= np.bincount(fresh // t, minlength=docs)
        if r & 1 or r < 8:
            stay = open_bins[doc] > 0
            if not stay.all():
                item, doc = item[stay], doc[stay]
    return out.reshape(docs, t)


def band_keys(sketch: np.ndarray, rows: int) -> np.ndarray:
    """(documents, bands) 64-bit keys of ``rows`` coordinates each; the band's number is part of a key."""
    docs, t = sketch.shape
    parts = sketch.reshape(docs, t // rows, rows)
    key = np.full(parts.shape[:2], np.uint64(0xC2B2AE3D27D4EB4F)) + np.arange(parts.shape[1], dtype=np.uint64)
    for k in range(rows):
        key = mix(key * np.uint64(0x9FB21C651E98DF25) + parts[:, :, k])
    return key.view(np.int64)


def slices(batch: pa.RecordBatch, column: str, most: int = 3 << 20) -> Iterator[pa.RecordBatch]:
    """Parts of a batch of about ``most`` bytes of text; a longer text is a part of its own."""
    _, offsets = text_bytes(batch.column(column))
    at = 0
    while at < batch.num_rows:
        end = max(at + 1, int(np.searchsorted(offsets, offsets[at] + most, side="right")) - 1)
        yield batch.slice(at, end - at)
        at = end
