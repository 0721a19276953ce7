"""Language-model scores by deleted interpolation of bigrams.

Counts of all words and word pairs of the training documents are gathered by hash:
every chunk of documents sends its distinct keys (with its own counts) to buckets,
the buckets add up and send each chunk the totals of its keys. So no table of the
corpus's n-grams is ever broadcast, a frequent word is one entry a chunk, and each
text is scored from its own keys' totals only.

Probabilities mix the bigram and unigram maximum-likelihood estimates and a uniform
floor. The weights depend on how often the context was seen (by powers of two). They
are learned by expectation-maximisation on the counts of one fold of the training
documents, whose own counts are deleted from the estimates meanwhile; the events
reach the driver as a histogram over context bucket and binned estimates, whose size
is bounded and which covers every event of the fold. Hashes have 64 bits.

Defined cases: a null or empty text is the end token alone; a null id hashes as the
empty string; with no training text all estimates fall to the uniform floor;
repeated rows count each time and score alike; a very long text makes a chunk of its
own, held with its tokens by one task; an empty table gives no rows; other columns of
the input play no part, whatever their names.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from glyphfold.llm.simhash_dedup import LOWER
from glyphfold.llm.suffix_dedup import NO_ID, PART_BYTES, answers, body_of, by_bucket, chunk_batches, gathered_blobs, mixed, packed, unpacked
from glyphfold.session import discard, release, settle

U = np.uint64
CHUNK_BYTES = 4 << 20
BUCKET_BYTES = 8 << 20
MAX_BUCKETS = 400_000
FOLDS, HELD_OUT, DELETED = 7, 2, 3
#: Context buckets: unseen, then by powers of two; bins of estimates: half octaves.
CONTEXTS, BINS = 24, 128
START, END = b"\r", b"\n"  # can't be words
VOCABULARY = -1
U32 = np.uint32


class _Ids(dict):
    def __missing__(self, word):
        self[word] = n = len(self)
        return n


class Tokens:
    """The tokens of a chunk as keys: distinct words and pairs in order of their hashes."""

    def __init__(self, body: bytes):
        raw = zstandard.decompress(body)
        n = int(np.frombuffer(raw, np.int64, 1)[0])
        self.docs = np.frombuffer(raw, np.int64, n, 8)
        lens = np.frombuffer(raw, np.int64, n, 8 + 8 * n)
        ids = _Ids()
        get = ids.__getitem__
        get(START), get(END)
        parts, at = [], 8 + 16 * n
        for size in lens.tolist():
            words = raw[at : at + size].translate(LOWER).split()
            at += size
            parts.append(np.fromiter(map(get, words), np.int64, len(words)))
        self.n_tokens = np.array([len(p) + 1 for p in parts], np.int64)
        ends = np.cumsum(self.n_tokens)
        self.starts = ends - self.n_tokens
        now = np.ones(int(ends[-1]) if n else 0, np.int64)
        now[np.delete(np.arange(len(now)), ends - 1)] = np.concatenate(parts) if parts else []
        before = np.roll(now, 1)
        before[self.starts] = 0
        hashes = np.fromiter(map(xxhash.xxh64_intdigest, ids), U, len(ids))
        order = np.argsort(hashes)
        rank = np.empty(len(order), np.int64)
        rank[order] = np.arange(len(order))
        self.words, self.word_at = hashes[order], rank[now]
        self.before_at = np.where(before == 0, -1, rank[before])
        pairs, inverse = np.unique(before * len(ids) + now, return_inverse=True)
        keys = mixed(hashes[pairs // len(ids)] * U(0x9E3779B97F4A7C15) + hashes[pairs % len(ids)])
        order = np.argsort(keys)
        rank = np.empty(len(order), np.int64)
        rank[order] = np.arange(len(order))
        self.pairs, self.pair_at = keys[order], rank[inverse]
        fold = np.array([zlib.crc32(b"" if d == NO_ID else b"%d" % d) % FOLDS for d in self.docs.tolist()], np.int64)
        self.held_out, self.deleted = fold == HELD_OUT, fold == DELETED
        self.kept = ~self.held_out & ~self.deleted

    def of_docs(self, docs: np.ndarray) -> np.ndarray:
        """Mask of the tokens of the documents in a mask."""
        return np.repeat(docs, self.n_tokens)


def key_batches(batches: Iterator[pa.RecordBatch], buckets: int) -> Iterator[pa.RecordBatch]:
    """A chunk's keys with its counts (kept training documents, deleted fold) by bucket.

    Words go to buckets from 0, pairs to those from ``buckets``.
    """
    for batch in batches:
        for chunk, body in zip(batch.column("chunk").to_pylist(), batch.column("body"), strict=True):
            t = Tokens(body.as_py())
            kept, gone = t.of_docs(t.kept), t.of_docs(t.deleted)
            rows = []
            for keys, at, base in ((t.words, t.word_at, 0), (t.pairs, t.pair_at, buckets)):
                mine = [np.bincount(at[m], minlength=len(keys)).astype(U32) for m in (kept, gone)]
                for b, own in by_bucket(((keys >> U(32)) * U(buckets)) >> U(32)):
                    rows.append((base + b, chunk, packed(keys[own], mine[0][own], mine[1][own])))
            cols = list(zip(*rows, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.binary())], ["bucket", "chunk", "body"])


def add_up(df: pd.DataFrame, buckets: int) -> pd.DataFrame:
    """Totals of each key for every chunk that asked; the bucket's words in training go to chunk -1."""
    bucket = int(df["bucket"].iloc[0])
    got = [unpacked(b, U, U32, U32) for b in df["body"]]
    keys, kept, gone = (np.concatenate(c) for c in zip(*got, strict=True))
    distinct, at = np.unique(keys, return_inverse=True)
    kept = np.bincount(at, kept, len(distinct))
    gone = np.bincount(at, gone, len(distinct))
    out = answers(df, got, np.stack([kept[at], gone[at]], axis=1).astype(np.int64), lambda x: packed(x[:, 0], x[:, 1]))
    if bucket < buckets:
        seen = np.array([(kept + gone > 0).sum(), (kept > 0).sum()], np.int64)
        out.loc[len(out)] = [VOCABULARY, bucket, seen.tobytes()]
    return out


def context_bucket(count: np.ndarray) -> np.ndarray:
    return np.minimum(np.floor(np.log2(np.maximum(count, 0.5))).astype(np.int64) + 1, CONTEXTS - 1)


def binned(p: np.ndarray) -> np.ndarray:
    """Half octaves of a probability; 0 for none."""
    with np.errstate(divide="ignore"):
        return np.where(p > 0, np.minimum(1 + np.floor(-2 * np.log2(np.where(p > 0, p, 1))), BINS - 1), 0).astype(np.int64)


def bin_value(b: np.ndarray) -> np.ndarray:
    return np.where(b > 0, np.minimum(2.0 ** (-(b - 0.5) / 2), 1.0), 0.0)


def resolve_chunk(df: pd.DataFrame, buckets: int, totals: dict) -> pd.DataFrame:
    """Counts behind every token of a chunk, and its part of the fold's histogram."""
    t = Tokens(body_of(df, -1))
    words = [np.concatenate(c) for c in zip(*gathered_blobs(df, 0, buckets, np.int64, np.int64), strict=True)]
    pairs = [np.concatenate(c) for c in zip(*gathered_blobs(df, buckets, 2 * buckets, np.int64, np.int64), strict=True)]
    if len(words[0]) != len(t.words) or len(pairs[0]) != len(t.pairs):
        raise ValueError("a chunk and its answers don't match")
    docs = [totals["kept_docs"], totals["deleted_docs"]]
    context = [np.where(t.before_at < 0, n, w[t.before_at]) for n, w in zip(docs, words, strict=True)]
    gone = t.of_docs(t.deleted)
    ch, cw, chw = context[0][gone], words[0][t.word_at][gone], pairs[0][t.pair_at][gone]
    cell = (context_bucket(ch) * BINS + binned(chw / np.maximum(ch, 1))) * BINS + binned(cw / max(totals["kept_tokens"], 1))
    cells, weight = np.unique(cell, return_counts=True)
    # a token's context count is the word count of the token before
    counts = packed(*((a + b)[at].astype(np.int64) for (a, b), at in ((words, t.word_at), (pairs, t.pair_at))))
    head = packed(t.docs, t.n_tokens, t.held_out.astype(np.int64))
    return pd.DataFrame({"head": [head], "counts": [counts], "cells": [cells.tolist()], "weights": [weight.tolist()]})


def learn(cells: np.ndarray, weight: np.ndarray, vocabulary: int, rounds: int = 60) -> np.ndarray:
    """Mixture weights (bigram, unigram, floor) for each context bucket."""
    bucket, b2, b1 = cells // (BINS * BINS), cells // BINS % BINS, cells % BINS
    p = np.stack([bin_value(b2), bin_value(b1), np.full(len(cells), 1 / (vocabulary + 1))], axis=1)
    mix = np.full((CONTEXTS, 3), 1 / 3)
    mix[0] = [0, 0.5, 0.5]
    for _ in range(rounds):
        share = mix[bucket] * p
        share *= (weight / share.sum(axis=1))[:, None]
        new = np.full((CONTEXTS, 3), 1e-6)
        new[:, 2] = 0.01  # the floor keeps some mass
        new[0, 0] = 0
        np.add.at(new, bucket, share)
        seen = np.bincount(bucket, weight, CONTEXTS) > 0
        mix[seen] = (new / new.sum(axis=1, keepdims=True))[seen]
    for b in np.flatnonzero(~seen):  # as the nearest bucket below that was seen
        if b > 1 and seen[1:b].any():
            mix[b] = mix[np.flatnonzero(seen[1:b])[-1] + 1]
    return mix


def score_batches(batches: Iterator[pa.RecordBatch], mix: np.ndarray, n_docs: int, tokens: int, vocabulary: int) -> Iterator[pa.RecordBatch]:
    names = ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"]
    for batch in batches:
        for head, counts in zip(batch.column("head"), batch.column("counts"), strict=True):
            docs, n, held = unpacked(head.as_py(), np.int64, np.int64, np.int64)
            cw, chw = unpacked(counts.as_py(), np.int64, np.int64)
            at = np.cumsum(n) - n
            ch = np.roll(cw, 1)
            ch[at] = n_docs
            w = mix[context_bucket(ch)]
            p = w[:, 0] * chw / np.maximum(ch, 1) + w[:, 1] * cw / max(tokens, 1) + w[:, 2] / (vocabulary + 1)
            base = np.log10((cw + 1) / (tokens + 1 * (vocabulary + 1)))
            sums = [np.add.reduceat(x, at) if len(at) else x for x in ((cw > 0).astype(np.int64), base, np.log10(p))]
            ids = pa.array([None if d == NO_ID else d for d in docs.tolist()], pa.int64())
            yield pa.RecordBatch.from_arrays([ids, pa.array(held == 1), pa.array(n), pa.array(sums[0]), pa.array(np.full(len(n), tokens)), pa.array(sums[1]), pa.array(sums[2])], names)


SCORED = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def lm_scores(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Unigram and interpolated log10 probabilities of every whole text."""
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    chunks = settle(rows.mapInArrow(lambda it: chunk_batches(it, CHUNK_BYTES), "chunk long, n_bytes long, body binary"), "lm_chunks")
    total = chunks.agg(F.coalesce(F.sum("n_bytes"), F.lit(0))).first()[0]
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    buckets = min(MAX_BUCKETS, max(2 * parts, total // BUCKET_BYTES))
    parts = max(parts, total // PART_BYTES)  # a task's share stays bounded as the input grows
    entry = "bucket long, chunk long, body binary"
    keys = chunks.select("chunk", "body").mapInArrow(lambda it: key_batches(it, buckets), entry)
    own = keys.repartition(parts, "bucket").groupBy("bucket").applyInPandas(lambda df: add_up(df, buckets), "chunk long, bucket long, body binary")
    totals = settle(own, "lm_totals")
    del keys, own
    release(spark)

    sizes = chunks.select("body").mapInArrow(size_batches, "kept_tokens long, deleted_tokens long, kept_docs long, deleted_docs long")
    known = sizes.agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in sizes.columns)).first().asDict()
    vocab = totals.where(F.col("chunk") == VOCABULARY).select("body").mapInArrow(vocabulary_batches, "seen long, kept long")
    vocabulary, kept_words = vocab.agg(F.coalesce(F.sum("seen"), F.lit(0)), F.coalesce(F.sum("kept"), F.lit(0))).first()

    texts = chunks.select("chunk", F.lit(-1).cast("long").alias("bucket"), "body")
    both = texts.unionByName(totals.where("chunk >= 0"))
    resolved = both.repartition(parts, "chunk").groupBy("chunk").applyInPandas(lambda df: resolve_chunk(df, buckets, known), "head binary, counts binary, cells array<long>, weights array<long>")
    resolved = settle(resolved, "lm_counts")
    discard(chunks)
    discard(totals)
    release(spark)
    cells = resolved.select(F.explode(F.arrays_zip("cells", "weights")).alias("c")).groupBy("c.cells").agg(F.sum("c.weights").alias("n")).collect()
    mix = learn(np.array([r[0] for r in cells], np.int64), np.array([r[1] for r in cells], float), kept_words)
    n = known["kept_tokens"] + known["deleted_tokens"]
    n_docs = known["kept_docs"] + known["deleted_docs"]
    return resolved.select("head", "counts").mapInArrow(lambda it: score_batches(it, mix, n_docs, n, vocabulary), SCORED)


def size_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Training tokens and documents of chunks, without hashing them."""
    for batch in batches:
        for body in batch.column("body"):
            raw = zstandard.decompress(body.as_py())
            n = int(np.frombuffer(raw, np.int64, 1)[0])
            docs, lens = np.frombuffer(raw, np.int64, n, 8), np.frombuffer(raw, np.int64, n, 8 + 8 * n)
            out, at = np.zeros(4, np.int64), 8 + 16 * n
            for d, size in zip(docs.tolist(), lens.tolist(), strict=True):
                fold = zlib.crc32(b"" if d == NO_ID else b"%d" % d) % FOLDS
                if fold != HELD_OUT:
                    out[int(fold == DELETED)] += len(raw[at : at + size].split()) + 1
                    out[2 + int(fold == DELETED)] += 1
                at += size
            yield pa.RecordBatch.from_arrays([pa.array([int(x)]) for x in out], ["kept_tokens", "deleted_tokens", "kept_docs", "deleted_docs"])


def vocabulary_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        got = [np.frombuffer(b.as_py(), np.int64) for b in batch.column("body")]
        yield pa.RecordBatch.from_arrays([pa.array([int(g[i]) for g in got], pa.int64()) for i in (0, 1)], ["seen", "kept"])


def query(spark, sf_dir: str) -> DataFrame:
    return lm_scores(spark.read.parquet(f"{sf_dir}/documents.parquet"))
