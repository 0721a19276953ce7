"""Exact removal of repeated byte strings by a sparse, range-partitioned suffix sort.

A suffix is sorted for a content-defined choice of starts: of the 20-byte grams in
every 50-byte string the one with the smallest hash is its anchor, so equal strings
have equal anchors and about one start in fifteen is kept. An anchor stands for
the consecutive strings it is chosen by; its context is the bytes they span.

1. Documents are written as chunks. Each chunk sorts the suffixes at its anchors by
   their leading 20 bytes (multikey quicksort by words of bytes; equal ones by a hash of
   the context), folds equal contexts to the smallest document and cuts the order at
   sampled splitters; buckets of all chunks meet, sort again and compare.
   A context also seen in a smaller document is repeated as a whole. A suffix whose
   leading bytes are shared by other contexts is open, as is one whose leading bytes
   touch a splitter, since its neighbours may lie beyond the boundary.
2. Open anchors meet others of the same leading bytes with their context itself, and
   its 50-byte strings are compared, found by hash and settled by bytes. Anchors that
   very many contexts share (the ends of a common line) are dealt out by string instead
   of by anchor, those strings as 64-bit hashes.
3. Chunks gather their answers and cut the repeated bytes.

Folding in the chunk keeps a string of very many documents to one entry a chunk, so
no bucket grows with a group of copies. Contexts are equal if their 20 leading bytes and
a 64-bit hash of the rest are. All steps pass through tables or shuffles that outlive
executors.

Defined cases: a null text is empty; a null id counts as larger than all others;
rows of equal id don't repeat each other; texts under 50 bytes are kept whole; very
long texts are handled in slices, but make one chunk each; an empty table gives no rows;
other columns of the input play no part, whatever their names.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from glyphfold.llm.lean import keep_small, trim
from glyphfold.session import discard, release, settle

#: Bytes of an anchor, from 16 to 24: longer ones are shared by chance less often, shorter ones are fewer.
GRAM = 20
SLICE = 1 << 18
CHUNK_BYTES = 4 << 20
BUCKET_BYTES = 4 << 20
MAX_BUCKETS = 400_000
#: Input bytes that a task of a shuffle stands for, beyond the session's number of partitions.
PART_BYTES = 64 << 20
#: Contexts of the same leading bytes above which they are compared string by string.
HOT_GRAM = 4000
#: At most so many chunks give starts to the sample that places the splitters.
SAMPLED_CHUNKS = 800
NO_ID = np.iinfo(np.int64).max
ROLL = np.uint64(0x9E3779B97F4A7C15)
U = np.uint64


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U(31))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


@lru_cache(maxsize=2)
def powers(n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Powers of the rolling base, of its inverse, and a random word per byte value."""
    one = np.ones(1, U)
    base = np.concatenate([one, np.full(n, ROLL, U)]).cumprod(dtype=U)
    inverse = U(pow(int(ROLL), -1, 1 << 64))
    back = np.concatenate([one, np.full(n, inverse, U)]).cumprod(dtype=U)
    return base, back, mixed(np.arange(1, 257, dtype=U) * U(0xD1342543DE82EF95))


def words_at(data: np.ndarray) -> np.ndarray:
    """The 8 bytes from every position as a little-endian integer."""
    n = len(data) - 7
    return np.ndarray(max(n, 0), "<u8", data.tobytes() + b"\0" * 8, strides=(1,)).astype(U)


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    span = 1
    while span * 2 <= width:
        x = np.minimum(x[:-span], x[span:])
        span *= 2
    return np.minimum(x[: len(x) - (width - span)], x[width - span :]) if width > span else x


class Slice:
    """Anchors of data[at:end]; ``ends`` has the end of the document for every byte position."""

    def __init__(self, data: np.ndarray, ends: np.ndarray, at: int, end: int, window: int):
        lo, hi = max(0, at - 2 * window), min(len(data), end + 2 * window)
        part = data[lo:hi]
        self.lo, self.window = lo, window
        base, back, letters = powers(SLICE + 4 * window + 64)
        self.prefix = np.concatenate([np.zeros(1, U), np.cumsum(letters[part] * base[: len(part)], dtype=U)])
        self.back = back
        empty = np.zeros(0, np.int64)
        self.start = self.first = self.last = empty
        grams = window - GRAM + 1
        if len(part) < window:
            self.lead = self.next = self.tail = self.context = np.zeros(0, U)
            return
        eight = words_at(part)
        n = len(part) - GRAM + 1
        rest = mixed(eight[8 : 8 + n] * U(0xA24BAED4963EE407) + eight[GRAM - 8 : GRAM - 8 + n])
        h = mixed(eight[:n] ^ rest) | U(1)
        low = sliding_min(h, grams)  # one a window
        whole = np.arange(lo, lo + len(low)) + window <= ends[lo : lo + len(low)]
        low = np.where(whole, low, U(0))
        padded = np.concatenate([np.zeros(grams - 1, U), low, np.zeros(max(0, len(h) - len(low)), U)])
        highest = ~sliding_min(~padded, grams)[: len(h)]  # of the windows that hold a gram
        start = np.flatnonzero(highest == h)
        start = start[(start + lo >= at) & (start + lo < end)]
        # the windows that a gram is chosen by follow each other: they lie in one run of equal minima
        turn = np.concatenate([[0], np.flatnonzero(low[1:] != low[:-1]) + 1, [len(low)]])
        reach = np.maximum(start - grams + 1, 0)
        run, mine = np.searchsorted(turn, reach, side="right") - 1, h[start]
        todo = np.arange(len(start))
        while len(todo):
            todo = todo[low[turn[run[todo]]] != mine[todo]]
            run[todo] += 1
        first, last = np.maximum(turn[run], reach), np.minimum(turn[run + 1] - 1, start)
        self.start, self.first, self.last = start + lo, first + lo, last + lo
        self.lead = eight[start].byteswap()
        self.next = eight[start + 8].byteswap()
        self.tail = (eight[start + 12] >> U(32)).astype(np.uint32).byteswap().astype(U)
        spot = (last - first).astype(U) * U(64) + (start - first).astype(U)
        self.context = mixed(self.span(first, last + window) + mixed(spot))

    def span(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Hashes of part[a:b], wherever they stand."""
        return (self.prefix[b] - self.prefix[a]) * self.back[a]

    def strings(self, starts: np.ndarray) -> np.ndarray:
        """Hashes of the windows at positions of the whole data."""
        a = starts - self.lo
        return mixed(self.span(a, a + self.window))


def packed(*columns: np.ndarray) -> bytes:
    """Columns of equal length, byte by byte of their values, compressed."""
    raw = b"".join(np.ascontiguousarray(c).view(np.uint8).reshape(len(c), c.dtype.itemsize).T.tobytes() for c in columns)
    return zstandard.compress(raw, 1)


def unpacked(blob: bytes, *types) -> list[np.ndarray]:
    raw = np.frombuffer(zstandard.decompress(blob), np.uint8)
    widths = [np.dtype(t).itemsize for t in types]
    n = len(raw) // sum(widths)
    out, at = [], 0
    for t, w in zip(types, widths, strict=True):
        out.append(np.ascontiguousarray(raw[at : at + n * w].reshape(w, n).T).view(t).reshape(n))
        at += n * w
    return out


def chunk_batches(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[pa.RecordBatch]:
    keep_small()
    part, seq = TaskContext.get().partitionId(), 0
    ids: list[int] = []
    texts: list[bytes] = []
    room = 0

    def out() -> pa.RecordBatch:
        nonlocal ids, texts, room, seq
        lens = np.array([len(t) for t in texts], np.int64)
        head = np.concatenate([[len(ids)], np.array(ids, np.int64), lens]).astype(np.int64)
        body = zstandard.compress(head.tobytes() + b"".join(texts), 3)
        row = pa.RecordBatch.from_arrays([pa.array([part << 32 | seq]), pa.array([int(lens.sum())]), pa.array([body], pa.binary())], ["chunk", "n_bytes", "body"])
        ids, texts, room, seq = [], [], 0, seq + 1
        return row

    for batch in batches:
        for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text"), strict=True):
            ids.append(NO_ID if doc is None else doc)
            texts.append((text.as_py() or "").encode())
            room += len(texts[-1])
            if room >= size:
                yield out()
    if ids:
        yield out()


class Chunk:
    def __init__(self, body: bytes, window: int):
        raw = zstandard.decompress(body)
        n = int(np.frombuffer(raw, np.int64, 1)[0])
        self.ids = np.frombuffer(raw, np.int64, n, 8)
        self.lens = np.frombuffer(raw, np.int64, n, 8 + 8 * n)
        self.data = np.frombuffer(raw, np.uint8, -1, 8 + 16 * n) if self.lens.sum() else np.zeros(0, np.uint8)
        self.ends = np.cumsum(self.lens)
        self.window = window

    def doc_of(self, at: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.ends, at, side="right")

    def slices(self) -> Iterator[Slice]:
        for at in range(0, len(self.data), SLICE):
            end = min(at + SLICE, len(self.data))
            lo, hi = max(0, at - 4 * self.window), min(len(self.data), end + 4 * self.window)
            a, b = np.searchsorted(self.ends, (lo, hi - 1), side="right")
            own = self.ends[a : b + 1]
            ends = np.repeat(own, np.diff(np.minimum(own, hi), prepend=lo))
            yield Slice(self.data, _Shifted(ends, lo), at, end, self.window)

    def anchors(self) -> tuple[list[np.ndarray], np.ndarray, np.ndarray, np.ndarray]:
        """Of all anchors: the sort keys (leading bytes in three words, context), document id, first and last window."""
        cols: list[list] = [[] for _ in range(7)]
        for s in self.slices():
            for c, v in zip(cols, (s.lead, s.next, s.tail, s.context, self.ids[self.doc_of(s.start)], s.first, s.last), strict=True):
                c.append(v)
        kinds = (U, U, U, U, np.int64, np.int64, np.int64)
        got = [np.concatenate(c) if c else np.zeros(0, t) for c, t in zip(cols, kinds, strict=True)]
        return got[:4], *got[4:]


class _Shifted:
    """An array that stands for a longer one from ``lo`` on."""

    def __init__(self, values: np.ndarray, lo: int):
        self.values, self.lo = values, lo

    def __getitem__(self, at: slice) -> np.ndarray:
        return self.values[at.start - self.lo : at.stop - self.lo]


#: Rows below which a part of the order is sorted word by word at once.
SMALL_SORT = 1 << 16


def word_order(keys: list[np.ndarray], order: np.ndarray) -> np.ndarray:
    """Rows of ``order`` sorted by the first word; runs of equal words go on to the next one."""
    order = order[np.argsort(keys[0][order], kind="stable")]
    run = np.zeros(len(order), np.int64)
    for depth in range(1, len(keys)):
        word = keys[depth - 1][order]
        new = np.ones(len(order), bool)
        new[1:] = (word[1:] != word[:-1]) | (run[1:] != run[:-1])
        run = np.cumsum(new)
        alone = new.copy()
        alone[:-1] &= new[1:]
        at = np.flatnonzero(~alone)
        if not len(at):
            break
        own = order[at]
        order[at] = own[np.lexsort((keys[depth][own], run[at]))]
    return order


def multikey_order(keys: list[np.ndarray]) -> np.ndarray:
    """Order of rows by their words: multikey quicksort.

    A part is split by the current word into rows below, at and above a pivot; rows at it
    go on to the next word, the others stay. Small parts are sorted word by word.
    """
    order = np.arange(len(keys[0]))
    todo = [(0, len(order), 0)]
    while todo:
        low, high, depth = todo.pop()
        if high - low < 2 or depth == len(keys):
            continue
        own = order[low:high]
        if high - low <= SMALL_SORT:
            order[low:high] = word_order(keys[depth:], own)
            continue
        word = keys[depth][own]
        some = np.sort(word[:: max(1, len(word) // 31)])
        pivot = some[len(some) // 2]
        below, above = word < pivot, word > pivot
        order[low:high] = np.concatenate([own[below], own[~(below | above)], own[above]])
        a, b = low + int(below.sum()), high - int(above.sum())
        todo += [(low, a, depth), (a, b, depth + 1), (b, high, depth)]
    return order


def changes(*columns: np.ndarray) -> np.ndarray:
    """True where a row of sorted columns differs from the one before."""
    new = np.ones(len(columns[0]), bool)
    if len(new):
        new[1:] = np.logical_or.reduce([c[1:] != c[:-1] for c in columns])
    return new


def folded(keys: list[np.ndarray], doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Order of the entries (one for equal keys, of the smallest document); entry of each row; its document."""
    order = multikey_order([*keys, doc])
    new = changes(*(k[order] for k in keys))
    entry = np.empty(len(order), np.int64)
    entry[order] = np.cumsum(new) - 1
    return order[new], entry, doc[order[new]]


def cuts_of(keys: list[np.ndarray], splitters: np.ndarray) -> np.ndarray:
    """Where the sorted entries reach each splitter."""
    low = np.searchsorted(keys[0], splitters[:, 0], side="left")
    high = np.searchsorted(keys[0], splitters[:, 0], side="right")
    for i in np.flatnonzero(high > low):  # within a run of equal words the next word decides
        a, b = low[i], high[i]
        for k, word in zip(keys[1:], splitters[i, 1:], strict=True):
            a, b = a + np.searchsorted(k[a:b], word, side="left"), a + np.searchsorted(k[a:b], word, side="right")
        low[i] = a
    return low


def suffix_batches(batches: Iterator[pa.RecordBatch], splitters: np.ndarray, window: int) -> Iterator[pa.RecordBatch]:
    keep_small()
    for batch in batches:
        for chunk, body in zip(batch.column("chunk").to_pylist(), batch.column("body"), strict=True):
            keys, doc, _, _ = Chunk(body.as_py(), window).anchors()
            keep, _, least = folded(keys, doc)
            keys = [k[keep] for k in keys]
            cut = np.concatenate([[0], cuts_of(keys, splitters), [len(keep)]])
            full = np.flatnonzero(cut[1:] > cut[:-1])
            lead, nxt, tail, context = keys[0], keys[1], keys[2].astype(np.uint32), keys[3]
            blobs = [packed(lead[a:b], nxt[a:b], tail[a:b], context[a:b], least[a:b]) for a, b in zip(cut[full], cut[full + 1], strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(full.astype(np.int64)), pa.array([chunk] * len(full), pa.int64()), pa.array(blobs, pa.binary())], ["bucket", "chunk", "body"])
            del keys, lead, nxt, tail, context, doc, keep, least, blobs
            trim()


def compare_suffixes(df: pd.DataFrame, splitters: np.ndarray, hot_gram: int) -> pd.DataFrame:
    """Per entry 0 (only here), 1 (context of a smaller document too), 2 (open) or 3 (open, of very many)."""
    keep_small()
    bucket = int(df["bucket"].iloc[0])
    got = [unpacked(b, U, U, np.uint32, U, np.int64) for b in df["body"]]
    *keys, doc = (np.concatenate(c) for c in zip(*got, strict=True))
    order = multikey_order([*keys, doc])
    keys, doc = [k[order] for k in keys], doc[order]
    gram_new, context_new = changes(*keys[:3]), changes(*keys)
    gram, ctx = np.cumsum(gram_new) - 1, np.cumsum(context_new) - 1
    least = doc[context_new][ctx]
    starts = np.flatnonzero(gram_new)
    contexts = np.add.reduceat(context_new.astype(np.int64), starts)
    several = (contexts > 1) & (np.minimum.reduceat(least, starts) < np.maximum.reduceat(least, starts))
    kind = np.where(several, np.where(contexts > hot_gram, 3, 2), 0)
    for i in (bucket - 1, bucket):  # what touches a splitter may have neighbours beyond it
        if 0 <= i < len(splitters):
            kind[np.logical_and.reduce([k[starts] == word for k, word in zip(keys[:3], splitters[i], strict=False)])] = 3
    state = np.where(doc > least, 1, kind[gram]).astype(np.uint8)
    back = np.empty(len(order), np.uint8)
    back[order] = state
    return answers(df, got, back)


def answers(df: pd.DataFrame, got: list, state: np.ndarray, pack=lambda x: zstandard.compress(x.tobytes(), 1)) -> pd.DataFrame:
    """Split the states again by the rows they belong to."""
    cut = np.cumsum([len(g[0]) for g in got])[:-1]
    return pd.DataFrame({"chunk": df["chunk"], "bucket": df["bucket"], "body": [pack(s) for s in np.split(state, cut)]}).reset_index(drop=True)


def gathered_blobs(df: pd.DataFrame, low: int, high: int, *types) -> list:
    """The columns answered by each bucket from ``low`` to ``high``, in order."""
    own = df[(df["bucket"] >= low) & (df["bucket"] < high)].sort_values("bucket")
    return [unpacked(b, *types) for b in own["body"]]


def gathered(df: pd.DataFrame, kind, low: int, high: int) -> np.ndarray:
    """The answers of buckets from ``low`` to ``high``, in order."""
    own = df[(df["bucket"] >= low) & (df["bucket"] < high)].sort_values("bucket")
    parts = [np.frombuffer(zstandard.decompress(b), kind) for b in own["body"]]
    return np.concatenate(parts) if parts else np.zeros(0, kind)


def body_of(df: pd.DataFrame, bucket: int) -> bytes:
    return df["body"][df["bucket"] == bucket].iloc[0]


def open_strings(chunk: Chunk, first: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All windows of the open anchors, once each, and their hashes."""
    size = last - first + 1
    at = np.unique(np.repeat(first - np.concatenate([[0], np.cumsum(size)[:-1]]), size) + np.arange(size.sum())) if len(first) else first
    if not len(at):
        return at, np.zeros(0, U)
    hashes = np.empty(len(at), U)
    base, back, letters = powers(SLICE + 4 * chunk.window + 64)
    for lo in range(0, len(chunk.data), SLICE):
        a, b = np.searchsorted(at, (lo, lo + SLICE))
        if b > a:
            part = chunk.data[lo : lo + SLICE + chunk.window]
            prefix = np.concatenate([np.zeros(1, U), np.cumsum(letters[part] * base[: len(part)], dtype=U)])
            j = at[a:b] - lo
            hashes[a:b] = mixed((prefix[j + chunk.window] - prefix[j]) * back[j])
    return at, hashes


def by_bucket(bucket: np.ndarray) -> Iterator[tuple[int, slice]]:
    cut = np.concatenate([np.flatnonzero(changes(bucket)), [len(bucket)]])
    for a, b in zip(cut[:-1], cut[1:], strict=True):
        yield int(bucket[a]), slice(a, b)


def resolve_chunk(df: pd.DataFrame, buckets: int, window: int) -> pd.DataFrame:
    """What a chunk keeps of the first comparison (buckets below -1), and what is open.

    Contexts go to buckets from 0, strings of very common anchors to those from ``buckets``.
    """
    keep_small()
    chunk = Chunk(body_of(df, -1), window)
    state = gathered(df, np.uint8, 0, 2 * buckets)
    keys, doc, first, last = chunk.anchors()
    keep, entry, least = folded(keys, doc)
    if len(least) != len(state):
        raise ValueError("a chunk and its answers don't match")
    name = int(df["chunk"].iloc[0])
    mine = state[entry] if len(entry) else np.zeros(0, np.uint8)
    mine = np.where(doc > least[entry], 1, mine) if len(entry) else mine
    hot = mine == 3
    at, hashes = open_strings(chunk, first[hot], last[hot])

    unsure = np.flatnonzero(state == 2)  # entries, to be sent in the order of their buckets
    gram = np.zeros(len(unsure), U)
    for k in keys[:3]:
        gram = mixed(gram ^ k[keep[unsure]])
    bucket = ((gram >> U(32)) * U(buckets)) >> U(32)
    order = np.argsort(bucket, kind="stable")
    unsure, bucket = unsure[order], bucket[order]
    place = np.full(len(state), -1)
    place[unsure] = np.arange(len(unsure))
    asks = np.flatnonzero(mine == 2)
    known = mine == 1
    rows = [
        (-2, name, packed(first[known], last[known])),
        (-3, name, packed(at)),
        (-4, name, packed(first[asks], last[asks], place[entry[asks]])),
    ]
    begin, end = first[keep[unsure]], last[keep[unsure]] + window
    for b, own in by_bucket(bucket):
        texts = b"".join(chunk.data[x:y].tobytes() for x, y in zip(begin[own], end[own], strict=True))
        size = (end[own] - begin[own]).astype(np.uint16)
        head = packed(least[unsure[own]], size)
        rows.append((b, name, len(head).to_bytes(4, "little") + head + zstandard.compress(texts, 3)))
    if len(at):
        keep, _, least = folded([hashes], chunk.ids[chunk.doc_of(at)])
        hashes = hashes[keep]
        for b, own in by_bucket(((hashes >> U(32)) * U(buckets)) >> U(32)):
            rows.append((buckets + b, name, packed(hashes[own], least[own])))
    return pd.DataFrame(rows, columns=["bucket", "chunk", "body"])


def compare_open(df: pd.DataFrame, buckets: int, window: int) -> pd.DataFrame:
    keep_small()
    return compare_strings(df) if df["bucket"].iloc[0] >= buckets else compare_contexts(df, window)


def compare_contexts(df: pd.DataFrame, window: int) -> pd.DataFrame:
    """Per context a mask of its strings that a smaller document has too."""
    got, texts = [], []
    for body in df["body"]:
        n = int.from_bytes(body[:4], "little")
        got.append(unpacked(body[4 : 4 + n], np.int64, np.uint16))
        texts.append(zstandard.decompress(body[4 + n :]))
    doc, size = (np.concatenate(c) for c in zip(*got, strict=True))
    size = size.astype(np.int64)
    data = np.frombuffer(b"".join(texts), np.uint8)
    begin = np.concatenate([[0], np.cumsum(size)[:-1]])
    masks = np.zeros(len(doc), np.uint64)
    base, back, letters = powers(SLICE + 4 * window + 64)
    hashes, owner, nth = [], [], []
    lo = 0
    while lo < len(doc):  # in slices of whole contexts
        hi = max(lo + 1, int(np.searchsorted(begin, begin[lo] + SLICE)))
        start = begin[lo]
        part = data[start : begin[hi - 1] + size[hi - 1]]
        prefix = np.concatenate([np.zeros(1, U), np.cumsum(letters[part] * base[: len(part)], dtype=U)])
        count = size[lo:hi] - window + 1
        who = np.repeat(np.arange(lo, hi), count)
        k = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        j = begin[who] - start + k
        hashes.append(mixed((prefix[j + window] - prefix[j]) * back[j]))
        owner.append(who)
        nth.append(k)
        lo = hi
    h, who, k = (np.concatenate(x) for x in (hashes, owner, nth))
    order = multikey_order([h, doc[who]])
    new = changes(h[order])
    first = order[new][np.cumsum(new) - 1]  # of equal hashes the one of the smallest document
    later = doc[who[order]] > doc[who[first]]
    hit, of = order[later], first[later]
    text = np.lib.stride_tricks.sliding_window_view(data, window)
    for lo in range(0, len(hit), 1 << 16):
        x, y = hit[lo : lo + (1 << 16)], of[lo : lo + (1 << 16)]
        x = x[(text[begin[who[x]] + k[x]] == text[begin[who[y]] + k[y]]).all(axis=1)]
        np.bitwise_or.at(masks, who[x], U(1) << k[x].astype(U))
    return answers(df, got, masks)


def compare_strings(df: pd.DataFrame) -> pd.DataFrame:
    """Per string 1 if a smaller document has it too."""
    got = [unpacked(b, U, np.int64) for b in df["body"]]
    hashes, doc = (np.concatenate(c) for c in zip(*got, strict=True))
    order = multikey_order([hashes, doc])
    new = changes(hashes[order])
    least = doc[order][new][np.cumsum(new) - 1]
    back = np.empty(len(order), np.uint8)
    back[order] = doc[order] > least
    return answers(df, got, back)


def finish_chunk(df: pd.DataFrame, buckets: int, window: int, with_text: bool) -> pd.DataFrame:
    keep_small()
    chunk = Chunk(body_of(df, -1), window)
    first, last = unpacked(body_of(df, -2), np.int64, np.int64)
    (at,) = unpacked(body_of(df, -3), np.int64)
    if len(at):
        state = gathered(df, np.uint8, buckets, 2 * buckets)
        at, hashes = open_strings(chunk, at, at)
        doc = chunk.ids[chunk.doc_of(at)]
        _, entry, least = folded([hashes], doc)
        at = at[np.where(doc > least[entry], 1, state[entry]) == 1]
    ask, ask_last, place = unpacked(body_of(df, -4), np.int64, np.int64, np.int64)
    if len(ask):
        masks = gathered(df, np.uint64, 0, buckets)[place]
        for k in range(int((ask_last - ask).max()) + 1):
            at = np.concatenate([at, ask[(masks >> U(k)) & U(1) == 1] + k])
    edge = np.zeros(len(chunk.data) + 1, np.int32)
    np.add.at(edge, first, 1)
    np.add.at(edge, last + window, -1)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + window, -1)
    gone = np.cumsum(edge[:-1]) > 0
    rows = []
    for doc, n, end in zip(chunk.ids.tolist(), chunk.lens.tolist(), chunk.ends.tolist(), strict=True):
        text, cut = chunk.data[end - n : end], gone[end - n : end]
        removed = int(cut.sum())
        spans = int(cut[0]) + int((cut[1:] & ~cut[:-1]).sum()) if removed else 0
        kept = (text[~cut] if removed else text).tobytes()
        rows.append((None if doc == NO_ID else doc, n, removed, spans, hashlib.sha256(kept).hexdigest(), kept if with_text else None))
    out = pd.DataFrame(rows, columns=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])
    return out.astype({"doc_id": "Int64"})


def sample_batches(batches: Iterator[pa.RecordBatch], keep_one_in: int, window: int) -> Iterator[pa.RecordBatch]:
    """Some starts of one slice of some chunks."""
    for batch in batches:
        for chunk, body in zip(batch.column("chunk").to_pylist(), batch.column("body"), strict=True):
            if int(mixed(np.array([chunk], U))[0]) % keep_one_in:
                continue
            c = Chunk(body.as_py(), window)
            c.data = c.data[: 1 << 17]
            keys, doc, _, _ = c.anchors()
            keep, _, _ = folded(keys, doc)
            yield pa.RecordBatch.from_arrays([pa.array(k[keep[::32]].view(np.int64)) for k in keys], list(KEYS))


#: The words suffixes are sorted by.
KEYS = ("lead", "next", "tail", "context")


def splitters_of(chunks: DataFrame, buckets: int, n_chunks: int, window: int) -> np.ndarray:
    """Suffixes that cut the order into buckets, from a sample of two starts a bucket and more."""
    rare = max(1, n_chunks // max(SAMPLED_CHUNKS, buckets // 64))
    rows = chunks.mapInArrow(lambda it: sample_batches(it, rare, window), ", ".join(f"{k} long" for k in KEYS)).toPandas()
    keys = [rows[c].to_numpy(np.int64).view(U) for c in KEYS]
    order = multikey_order(keys)
    at = order[np.linspace(0, len(order), buckets + 1)[1:-1].astype(np.int64)] if len(order) else order
    return np.unique(np.stack([k[at] for k in keys], axis=1), axis=0) if len(at) else np.zeros((0, len(KEYS)), U)


def suffix_dedup(docs: DataFrame, window: int = 50, id_col: str = "doc_id", text_col: str = "text", with_text: bool = True, hot_gram: int = HOT_GRAM) -> DataFrame:
    """Per document its bytes, the bytes and runs removed, and what is kept."""
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    chunks = settle(rows.mapInArrow(lambda it: chunk_batches(it, CHUNK_BYTES), "chunk long, n_bytes long, body binary"), "chunks")
    n_chunks, total = chunks.agg(F.count("*"), F.coalesce(F.sum("n_bytes"), F.lit(0))).first()
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    buckets = min(MAX_BUCKETS, max(4 * parts, total // BUCKET_BYTES))
    splitters = splitters_of(chunks, buckets, n_chunks, window)

    parts = max(parts, total // PART_BYTES)  # a task's share stays bounded as the input grows
    entry = "chunk long, bucket long, body binary"
    suffixes = chunks.select("chunk", "body").mapInArrow(lambda it: suffix_batches(it, splitters, window), "bucket long, chunk long, body binary")
    states = settle(suffixes.repartition(parts, "bucket").groupBy("bucket").applyInPandas(lambda df: compare_suffixes(df, splitters, hot_gram), entry), "suffix_states")
    del suffixes
    release(spark)

    texts = chunks.select("chunk", F.lit(-1).cast("long").alias("bucket"), "body")
    known = settle(  # what the states said is in there
        texts.unionByName(states).repartition(parts, "chunk").groupBy("chunk").applyInPandas(lambda df: resolve_chunk(df, buckets, window), "bucket long, chunk long, body binary"), "open_strings"
    )
    discard(states)
    release(spark)
    strings = known.where("bucket >= 0").repartition(parts, "bucket").groupBy("bucket").applyInPandas(lambda df: compare_open(df, buckets, window), entry)
    last = texts.unionByName(known.where("bucket < 0")).unionByName(strings)
    out = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary"
    return last.repartition(parts, "chunk").groupBy("chunk").applyInPandas(lambda df: finish_chunk(df, buckets, window, with_text), out)


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return suffix_dedup(docs, with_text=False).drop("kept")
