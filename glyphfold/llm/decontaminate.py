"""Benchmark decontamination by SimHash over item-sized windows.

For every benchmark item the windows of a document with as many words as the item are
fingerprinted: the SimHash of a window's words, from running sums of their bits. Windows
without a single shingle of an item of that length can't be like one and are passed over.
Fingerprints are looked up in a multi-index: with one block more than the radius has
bits, a fingerprint within the radius agrees in at least one whole block, so all items
within the radius are found. Hits are settled by the exact similarity of word shingles,
weighted by their counts. At similarity 0.8 the radius of 20 bits is a matter of chance
(about four standard deviations); tests and README compare with brute force.

Words are lower-cased runs of characters other than ASCII punctuation and white
space. The index of the benchmark is small; a benchmark of more than ``block_bytes``
is handled in blocks of that size, one index at a time.

Defined cases: null or empty texts and items have no words and never match; an item
shorter than a shingle is one shingle; a document shorter than the item is its own one
window; equal items are all reported; of equally similar windows the first counts;
repeated rows of a document give the same row each; very long texts are read in segments
that overlap by the longest item; with no items or documents there are no rows; other
columns of the input are left alone, whatever their names.
"""

from __future__ import annotations

import re
from collections import Counter, defaultdict
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: ASCII letters, digits and all bytes above 127 make words.
WORD_BYTES = bytes(c if c > 127 or chr(c).isalnum() else 32 for c in range(256))
U = np.uint64
BITS = np.arange(64, dtype=U)
SPACE = re.compile(r"\s")
FOUND = "doc_id long, item_id long, start_word long, n_words long, distance int, similarity double"


def words_of(text: str | None) -> list[bytes]:
    return (text or "").lower().encode("utf-8", "replace").translate(WORD_BYTES).split()


def word_hash(word: bytes) -> int:
    return xxhash.xxh64_intdigest(word) | 1


def gram_hashes(words: np.ndarray, width: int) -> np.ndarray:
    """Hashes of the runs of ``width`` words, from their word hashes."""
    n = len(words) - width + 1
    if n <= 0:
        return np.zeros(0, U)
    h = np.zeros(n, U)
    for k in range(width):
        h = h * U(0x9E3779B97F4A7C15) + words[k : k + n]
        h ^= h >> U(29)
    return h


class MultiIndex:
    """Fingerprints by the values of ``radius + 1`` blocks of their bits."""

    def __init__(self, radius: int, fps: list[int]):
        edges = np.linspace(0, 64, radius + 2).astype(int)
        self.radius = radius
        self.fps = np.array(fps, U)
        self.blocks = []
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            shift, mask = U(a), U((1 << int(b - a)) - 1)
            values, inverse = np.unique(self.fps >> shift & mask, return_inverse=True)
            self.blocks.append((shift, mask, values, [np.flatnonzero(inverse == v) for v in range(len(values))]))

    def within(self, prints: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Numbers of prints and of the fingerprints within the radius of each, and their distances."""
        found = np.zeros((len(prints), len(self.fps)), bool)
        for shift, mask, values, owners in self.blocks:
            own = prints >> shift & mask
            place = np.minimum(np.searchsorted(values, own), len(values) - 1)
            hit = values[place] == own
            for v, who in enumerate(owners):
                rows = np.flatnonzero(hit & (place == v))
                found[rows[:, None], who] = True
        w, i = np.nonzero(found)
        distance = np.bitwise_count(prints[w] ^ self.fps[i])
        near = distance <= self.radius
        return w[near], i[near], distance[near]


def window_prints(words: np.ndarray, starts: np.ndarray, size: int) -> np.ndarray:
    """SimHash of the windows of ``size`` words at ascending starts."""
    low = int(starts[0])
    part = words[low : int(starts[-1]) + size]
    sums = np.zeros((len(part) + 1, 64), np.int32)
    np.cumsum((part[:, None] >> BITS) & U(1), axis=0, dtype=np.int32, out=sums[1:])
    ones = sums[starts - low + size] - sums[starts - low]
    return ((2 * ones > size).astype(U) << BITS).sum(axis=1, dtype=U)


def windows_with(at: np.ndarray, width: int, size: int, n_words: int) -> np.ndarray:
    """Starts of all windows of ``size`` words that hold one of the shingles at ``at``."""
    edge = np.zeros(n_words - size + 2, np.int64)
    np.add.at(edge, np.clip(at - (size - width), 0, n_words - size + 1), 1)
    np.add.at(edge, np.clip(at + 1, 0, n_words - size + 1), -1)
    return np.flatnonzero(np.cumsum(edge[:-1]) > 0)


def segments(text: str | None, room: int, overlap: int, chars: int = 1 << 20) -> Iterator[tuple[int, list[bytes]]]:
    """The words of a text, about ``room`` at a time, each time with the last ``overlap`` ones of before, and their place."""
    text = text or ""
    words, first, at = [], 0, 0
    while at < len(text):
        cut = SPACE.search(text, at + chars)
        end = cut.start() if cut else len(text)
        words += words_of(text[at:end])
        at = end
        if len(words) >= room and at < len(text):
            yield first, words
            first += len(words) - overlap
            words = words[len(words) - overlap :]
    yield first, words


class Benchmark:
    """What executors need of the items: word and shingle hashes and a multi-index per length."""

    #: Windows that are fingerprinted at a time, and words of a text that are held at a time.
    WINDOWS, WORDS = 4096, 500_000

    def __init__(self, items: list[tuple[int, str | None]], width: int, similarity: float, radius: int):
        self.similarity, self.width = similarity, width
        self.vocab: dict[bytes, int] = {}
        self.grams: list[Counter] = []
        lengths: dict[int, dict[int, set]] = defaultdict(lambda: defaultdict(set))  # width, shingle: lengths
        prints: dict[int, list] = defaultdict(list)
        self.ids = []
        for item, text in items:
            words = words_of(text)
            if not words:
                continue
            self.vocab.update((w, word_hash(w)) for w in words)
            h = np.array([self.vocab[w] for w in words], U)
            n = len(words)
            own = gram_hashes(h, min(width, n))
            for g in own.tolist():
                lengths[min(width, n)][g].add(n)
            prints[n].append((int(window_prints(h, np.zeros(1, np.int64), n)[0]), len(self.ids)))
            self.grams.append(Counter(own.tolist()))
            self.ids.append(item)
        self.index = {n: (MultiIndex(radius, [p for p, _ in own]), [k for _, k in own]) for n, own in prints.items()}
        self.longest = max(prints, default=0)
        self.known = {}
        for w, table in lengths.items():
            grams = np.array(sorted(table), U)
            seen = np.zeros(1 << 20, bool)
            seen[grams >> U(44)] = True
            self.known[w] = (grams, [sorted(table[g]) for g in grams.tolist()], seen)

    def hits(self, words: list[bytes]) -> dict[int, list[int]]:
        """Starts of the shingles of items, by the item's length."""
        h = np.fromiter(map(self.vocab.get, words, repeat(0)), U, len(words))
        out: dict[int, list[int]] = defaultdict(list)
        for width, (grams, lengths, seen) in self.known.items():
            g = gram_hashes(h, width)
            at = np.flatnonzero(seen[g >> U(44)])
            if len(at):
                place = np.searchsorted(grams, g[at])
                place[place == len(grams)] = 0
                ok = grams[place] == g[at]
                for s, p in zip(at[ok].tolist(), place[ok].tolist(), strict=True):
                    for n in lengths[p]:
                        out[n].append(s)
        return out

    def best_windows(self, text: str | None) -> dict[int, tuple]:
        """Of each item like enough, its best window: (-similarity, start, words, distance)."""
        best: dict[int, tuple] = {}
        for first, words in segments(text, self.WORDS + 2 * self.longest, self.longest):
            hits = self.hits(words)
            if not hits:
                continue
            h = np.fromiter((self.vocab.get(w) or word_hash(w) for w in words), U, len(words))
            for n, at in sorted(hits.items()):
                width, size = min(self.width, n), min(n, len(words))  # a shorter document is its own one window
                if size < width:
                    continue
                starts = windows_with(np.array(at), width, size, len(words))
                for cut in range(0, len(starts), self.WINDOWS):
                    self.settle_windows(h, starts[cut : cut + self.WINDOWS], n, size, width, first, best)
        return best

    def settle_windows(self, h: np.ndarray, starts: np.ndarray, n: int, size: int, width: int, first: int, best: dict) -> None:
        index, keys = self.index[n]
        runs = np.split(starts, np.flatnonzero(np.diff(starts) > size) + 1)
        prints = np.concatenate([window_prints(h, run, size) for run in runs])
        at, last = -1, Counter()
        for w, i, distance in zip(*index.within(prints), strict=True):
            s, key = int(starts[w]), keys[i]
            if s != at:
                at, last = s, Counter(gram_hashes(h[s : s + size], width).tolist())
            other = self.grams[key]
            both = sum(min(c, other[g]) for g, c in last.items() if g in other)
            j = both / (last.total() + other.total() - both)
            if j >= self.similarity and (key not in best or (-j, first + s) < best[key][:2]):
                best[key] = (-j, first + s, size, int(distance))

    def batches(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text"), strict=True):
                for key, (j, s, n, d) in sorted(self.best_windows(text.as_py()).items()):
                    rows.append((doc, self.ids[key], s, n, d, -j))
            types = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.float64())
            names = ["doc_id", "item_id", "start_word", "n_words", "distance", "similarity"]
            cols = list(zip(*rows, strict=True)) if rows else [()] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names)


def indexes(benchmark: DataFrame, item_col: str = "item_id", item_text_col: str = "text", width: int = 5, similarity: float = 0.8, radius: int = 20, block_bytes: int = 8 << 20) -> Iterator[Benchmark]:
    """The benchmark's items in blocks of about ``block_bytes``, an index each."""
    items = benchmark.select(F.col(item_col).cast("long").alias("item_id"), F.col(item_text_col).alias("text"))
    total = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = -(-total // block_bytes) or 1
    for b in range(blocks):
        own = items if blocks == 1 else items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == b)
        yield Benchmark([(r.item_id, r.text) for r in own.collect()], width, similarity, radius)


def contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", **options) -> DataFrame:
    """``(doc_id, item_id, start_word, n_words, distance, similarity)``: best window of every item found in a document."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    out = None
    for index in indexes(benchmark, item_col, item_text_col, **options):
        part = rows.mapInArrow(index.batches, FOUND)
        out = part if out is None else out.unionByName(part)
    return out


def clean_batches(batches: Iterator[pa.RecordBatch], index: Benchmark, text_col: str) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        hold = pa.array([not index.best_windows(t.as_py()) for t in batch.column(text_col)], pa.bool_())
        yield batch.filter(hold)


def decontaminate(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", **options) -> DataFrame:
    """The rows of ``docs`` in which no benchmark item is found, columns unchanged; each row is judged by its own text."""
    for index in indexes(benchmark, item_col, item_text_col, **options):
        docs = docs.mapInArrow(lambda it, index=index: clean_batches(it, index, text_col), docs.schema)
    return docs


def query(spark, sf_dir: str) -> DataFrame:
    return contaminated(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
