"""Best-fit-decreasing packing of tokenised documents into fixed windows.

Each task packs what it reads, in groups of a bounded number of tokens, so nothing is
shuffled and a lost task is repeated alone.  Documents longer than a window are first cut
into full windows; the rests are placed in decreasing order of length into the tightest open
window, found by a segment tree over remaining capacities.  Then the emptiest windows are
dissolved into the gaps of the others and the very last one is cut into powers of two.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Callable, Iterator
from itertools import repeat
from unicodedata import is_normalized

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagewise.llm import texthash

WINDOW = 4096
GROUP_TOKENS = 4 << 20
BLOCK = 2 << 20  # bytes of text whose words are told apart at once
ENCODE_WORDS = 1 << 13  # new words given to the tokenizer at once: its results take some hundred bytes a word
_PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


class CapacityTree:
    """A segment tree whose leaves are remaining capacities 0..window, with the open windows of each."""

    def __init__(self, window: int):
        self.size = 1 << window.bit_length()
        self.any = bytearray(2 * self.size)
        self.bins: list[list[int]] = [[] for _ in range(window + 1)]

    def put(self, capacity: int, number: int) -> None:
        self.bins[capacity].append(number)
        k = capacity + self.size
        while k and not self.any[k]:
            self.any[k] = 1
            k >>= 1

    def take(self, length: int) -> tuple[int, int] | None:
        """(capacity, window) of the tightest open window that holds ``length``; it is taken out."""
        k = length + self.size
        if not self.any[k]:
            # up to the first subtree on the right that has a window, then down to its leftmost leaf
            while k > 1 and (k & 1 or not self.any[k ^ 1]):
                k >>= 1
            if k <= 1:
                return None
            k ^= 1
            while k < self.size:
                k = 2 * k if self.any[2 * k] else 2 * k + 1
        capacity = k - self.size
        number = self.bins[capacity].pop()
        if not self.bins[capacity]:
            while k and not (k < self.size and (self.any[2 * k] or self.any[2 * k + 1])):
                self.any[k] = 0
                k >>= 1
        return capacity, number


def best_fit_decreasing(lengths: list[int], window: int) -> list[list[int]]:
    """Indices of the pieces of each window; every length is between 1 and ``window``."""
    tree, windows = CapacityTree(window), []
    for i in sorted(range(len(lengths)), key=lambda i: (-lengths[i], i)):
        found = tree.take(lengths[i])
        if found is None:
            windows.append([i])
            capacity, number = window, len(windows) - 1
        else:
            capacity, number = found
            windows[number].append(i)
        if capacity > lengths[i]:
            tree.put(capacity - lengths[i], number)
    return windows


def plan_windows(sizes: list[int], window: int) -> list[list[tuple[int, int, int]]]:
    """sizes of documents -> windows of (document, start, length); a document of size 0 is in none."""
    full = [[(i, k, window)] for i, n in enumerate(sizes) for k in range(0, n - window + 1, window)]
    rest = [(i, n - n % window, n % window) for i, n in enumerate(sizes) if n % window]
    bins = [[rest[k] for k in own] for own in best_fit_decreasing([x[2] for x in rest], window)]
    used = [sum(x[2] for x in own) for own in bins]
    order = sorted(range(len(bins)), key=lambda k: (-used[k], k))
    head, tail = 0, len(order) - 1
    # the emptiest window's pieces fill, cut where needed, the gaps of the fullest
    while head < tail:
        target, source = order[head], order[tail]
        gap = window - used[target]
        if not gap:
            head += 1
            continue
        i, start, length = bins[source].pop()
        moved = min(gap, length)
        bins[target].append((i, start, moved))
        used[target] += moved
        used[source] -= moved
        if length > moved:
            bins[source].append((i, start + moved, length - moved))
        if not used[source]:
            tail -= 1
    out = full + [own for own, n in zip(bins, used) if n == window]
    for own, n in zip(bins, used):
        if 0 < n < window:
            out += _powers_of_two(own, n)
    return out


def _powers_of_two(pieces: list[tuple[int, int, int]], total: int) -> list[list[tuple[int, int, int]]]:
    out, pieces = [], list(pieces)
    for bit in range(total.bit_length() - 1, -1, -1):
        room, own = total & (1 << bit), []
        while room:
            i, start, length = pieces.pop()
            moved = min(room, length)
            own.append((i, start, moved))
            room -= moved
            if length > moved:
                pieces.append((i, start + moved, length - moved))
        if own:
            out.append(own)
    return out


class WordTokens:
    """Token ids of texts by a tokenizer that lower-cases, drops white space and never crosses it.

    The ids of a text are those of its words; a full stop or comma after a letter is a word of its
    own, as the tokenizer splits there too.  Ids of words are kept by the words' bytes, of at most
    ``most`` words; a full table starts anew.
    New words of plain letters are encoded many at once, told apart by the mark of a word's
    last token.  Texts that may hold the name of a special token go to the tokenizer whole.
    """

    def __init__(self, path: str, most: int = 1 << 19):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        vocabulary = self.tokenizer.get_vocab(with_added_tokens=True)
        self.last = np.zeros(max(vocabulary.values()) + 1, dtype=bool)
        self.last[[i for x, i in vocabulary.items() if x.endswith("</w>")]] = True
        self.most = most
        self._clear()
        texthash.give_back()  # what parsing the vocabulary left behind

    def _clear(self) -> None:
        self.known: dict[bytes, int] = {}  # the row of a word in ``spans``
        self.spans = np.zeros((1 << 14, 2), dtype=np.int64)  # start and number of a word's ids
        self.ids = np.zeros(1 << 18, dtype="<u4")
        self.used = 0

    def _rows(self, words: list[bytes]) -> np.ndarray:
        """Rows of the words, -1 where unknown."""
        return np.fromiter(map(self.known.get, words, repeat(-1)), dtype=np.int64, count=len(words))

    def _add(self, words: list[bytes]) -> None:
        ids = self._encode([w.decode("utf-8", "replace") for w in words])
        sizes = np.array([len(x) for x in ids], dtype=np.int64)
        total, row = int(sizes.sum()), len(self.known)
        if self.used + total > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros(max(total, len(self.ids)), dtype="<u4")])
        if row + len(words) > len(self.spans):
            self.spans = np.concatenate([self.spans, np.zeros((max(len(words), len(self.spans)), 2), dtype=np.int64)])
        self.ids[self.used : self.used + total] = np.concatenate(ids)
        self.spans[row : row + len(words), 0] = self.used + np.cumsum(sizes) - sizes
        self.spans[row : row + len(words), 1] = sizes
        self.used += total
        self.known.update(zip(words, range(row, row + len(words))))

    def _encode(self, words: list[str]) -> list[np.ndarray]:
        plain = [x for x in words if x.isalpha() and is_normalized("NFC", x) and x.lower().isalpha()]
        done: dict[str, np.ndarray] = {}
        if plain:
            ids = np.array(self.tokenizer.encode_batch_fast([" ".join(plain)], add_special_tokens=False)[0].ids, dtype="<u4")
            ends = np.flatnonzero(self.last[ids]) + 1
            if len(ends) == len(plain) and ends[-1] == len(ids):
                cuts = ends.tolist()
                done = {x: ids[a:b] for x, a, b in zip(plain, [0, *cuts], cuts)}
        rest = [x for x in words if x not in done]
        if rest:
            found = self.tokenizer.encode_batch_fast(rest, add_special_tokens=False)
            done |= {x: np.array(e.ids, dtype="<u4") for x, e in zip(rest, found)}
        return [done[x] for x in words]

    def _block(self, raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, ids of each document) of a block whose words are all whole."""
        starts, ends = texthash.word_spans(raw, offsets)
        if not len(starts):
            return np.zeros(0, dtype="<u4"), np.zeros(len(offsets) - 1, dtype=np.int64)
        stop = raw[ends - 1]
        before = raw[np.maximum(ends - 2, starts)]
        lead = raw[np.maximum(ends - 3, starts)]
        letter = ((before | 32) >= 97) & ((before | 32) <= 122)
        letter |= (lead == 0xC3) & (before >= 0x80) & (before != 0x97) & (before != 0xB7) & (ends - starts > 2)
        cut = ((stop == 44) | (stop == 46)) & letter & (ends - starts > 1)
        order = np.cumsum(cut) - cut + np.arange(len(starts))
        a, b = np.empty(len(starts) + int(cut.sum()), dtype=np.int64), np.empty(len(starts) + int(cut.sum()), dtype=np.int64)
        a[order], b[order] = starts, ends - cut
        a[order[cut] + 1], b[order[cut] + 1] = ends[cut] - 1, ends[cut]
        # letters that a combining mark may follow stay as they are: marks join some small letters only
        alone = np.append(raw[1:], 0) < 0xCC
        code, words = texthash.distinct_words(np.where(alone, texthash.LOWER[raw], raw), a, b)
        rows = self._rows(words)
        if (rows < 0).any():
            new = np.flatnonzero(rows < 0)
            if len(self.known) + len(new) > self.most:
                self._clear()
                new = np.arange(len(words))
            rows[new] = len(self.known) + np.arange(len(new))
            for k in range(0, len(new), ENCODE_WORDS):
                self._add([words[i] for i in new[k : k + ENCODE_WORDS].tolist()])
        rows = rows[code]
        at, size = self.spans[rows, 0], self.spans[rows, 1]
        before = np.cumsum(size) - size
        ids = self.ids[np.repeat(at - before, size) + np.arange(int(size.sum()))]
        doc = np.searchsorted(offsets, a, side="right") - 1
        return ids, np.bincount(doc, weights=size, minlength=len(offsets) - 1).astype(np.int64)

    def __call__(self, texts: pa.Array) -> list[np.ndarray]:
        """Ids of each text."""
        raw, offsets = texthash.text_bytes(texts)
        parts, counts = [], np.zeros(len(offsets) - 1, dtype=np.int64)
        for begin, end in texthash.blocks(raw, offsets, BLOCK):
            ids, own = self._block(raw[begin:end], np.clip(offsets - begin, 0, end - begin))
            parts.append(ids)
            counts += own
        ids = np.concatenate(parts) if parts else np.zeros(0, dtype="<u4")
        cuts = np.cumsum(counts)
        out = [ids[x:y] for x, y in zip(cuts - counts, cuts)]
        pipes = np.flatnonzero((raw[:-1] == 60) & (raw[1:] == 124))  # <|
        for i in np.unique(np.searchsorted(offsets, pipes, side="right") - 1).tolist():
            text = raw[offsets[i] : offsets[i + 1]].tobytes().decode()
            out[i] = np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, dtype="<u4")
        return out


_TOKENS: dict[str, WordTokens] = {}


def word_tokens(path: str) -> WordTokens:
    """One table for all tasks of a Python worker."""
    if path not in _TOKENS:
        _TOKENS[path] = WordTokens(path)
    return _TOKENS[path]


def _packer(tokens: Callable[[], Callable[[pa.Array], list[np.ndarray]]], end_id: int, window: int, group: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        np.seterr(over="ignore")
        encode = tokens()
        end = np.array([end_id], dtype="<u4")
        number = TaskContext.get().partitionId() << 40
        ids: list = []
        held: list[np.ndarray] = []
        total = 0

        def flush() -> pa.RecordBatch:
            nonlocal number, total
            sizes = [len(x) for x in held]
            rows = []
            for own in plan_windows(sizes, window):
                at = 0
                for i, start, length in own:
                    rows.append((ids[i], start, length, zlib.crc32(held[i][start : start + length]), sizes[i], number, at))
                    at += length
                number += 1
            ids.clear()
            held.clear()
            total = 0
            cols = list(zip(*rows)) or [()] * 7
            names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
            return pa.RecordBatch.from_arrays([pa.array(c, type=pa.int64()) for c in cols], names=names)

        for batch in batches:
            for part in texthash.slices(batch, "text", BLOCK):
                for doc, own in zip(part.column("doc_id").to_pylist(), encode(part.column("text"))):
                    ids.append(doc)
                    held.append(np.concatenate([own, end]))
                    total += len(held[-1])
                    if total >= group:
                        yield flush()
                texthash.trim()  # what a block took would add up beside the JVM
        if held:
            yield flush()
        texthash.give_back()

    return run


def pack(docs: DataFrame, tokenizer_path: str, end_id: int = 2, window: int = WINDOW, group_tokens: int = GROUP_TOKENS) -> DataFrame:
    """docs(doc_id, text, ...) -> pieces (doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset).

    A document's ids are its text's and then ``end_id``; a null or empty text has only that.
    Each id lies in exactly one piece; pieces of a sequence are gapless from offset 0.  All sequences
    are full but at most one per task and group, whose rest is cut into powers of two.
    Repeated and null doc_ids are packed like others; no rows give no pieces.
    """
    run = _packer(lambda: word_tokens(tokenizer_path), end_id, window, group_tokens)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, _PIECES)
