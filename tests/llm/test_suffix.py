import hashlib
import random

import numpy as np
import pytest
import zstandard

from glyphfold.llm import suffix_dedup as sd


def brute(docs, window=50):
    data = {i: (t or "").encode() for i, t in docs}
    least = {}
    for i, b in data.items():
        for j in range(len(b) - window + 1):
            g = b[j : j + window]
            least[g] = min(least.get(g, i), i)
    out = {}
    for i, b in data.items():
        gone = np.zeros(len(b), bool)
        for j in range(len(b) - window + 1):
            if least[b[j : j + window]] < i:
                gone[j : j + window] = True
        kept = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        spans = sum(1 for k in range(len(gone)) if gone[k] and (k == 0 or not gone[k - 1]))
        out[i] = (len(b), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest())
    return out


def corpus(seed, n=60):
    random.seed(seed)
    vocab = ["the", "of", "ëin", "ab", "c", "ding", "x" * 30]
    say = lambda k: " ".join(random.choices(vocab, k=k))
    shared = [say(40) for _ in range(4)] + ["License line " + say(8)]
    texts = [None, "", "short", "a" * 49, "a" * 50, "a" * 300, "a" * 120 + "b", "ab" * 100, say(2000)]
    for _ in range(n):
        texts.append(say(random.randint(0, 60)) + random.choice(shared + [""])[random.randint(0, 9) :] + say(random.randint(0, 60)))
    texts += [texts[8], texts[12], texts[12], texts[13][:-1] + "Z"]
    ids = random.sample(range(1000), len(texts))
    return list(zip(ids, texts, strict=True))


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_matches_brute_force(spark, monkeypatch, seed):
    if seed == 2:  # many chunks and buckets
        for name, value in (("CHUNK_BYTES", 4000), ("BUCKET_BYTES", 500)):
            monkeypatch.setattr(sd, name, value)
    docs = corpus(seed)
    df = spark.createDataFrame([(i, t, 1) for i, t in docs], "doc_id long, text string, chunk int").repartition(3)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in sd.suffix_dedup(df, hot_gram=1 if seed == 3 else 4000).collect()}
    assert got == brute(docs)


def test_slices_give_the_same_anchors(monkeypatch):
    texts = [(t or "").encode() for _, t in corpus(5)]
    head = np.concatenate([[len(texts)], np.arange(len(texts)), [len(t) for t in texts]]).astype(np.int64)
    body = zstandard.compress(head.tobytes() + b"".join(texts))
    flat = lambda got: [*got[0], *got[1:]]
    whole = flat(sd.Chunk(body, 50).anchors())
    monkeypatch.setattr(sd, "SLICE", 700)
    sd.powers.cache_clear()
    chunk = sd.Chunk(body, 50)
    parts = flat(chunk.anchors())
    at, hashes = sd.open_strings(chunk, whole[5], whole[6])
    monkeypatch.undo()
    sd.powers.cache_clear()
    assert all((a == b).all() for a, b in zip(whole, parts, strict=True))
    _, again = sd.open_strings(sd.Chunk(body, 50), whole[5], whole[6])
    assert (hashes == again).all()
    every = [a for s, n in zip(np.cumsum(head[1 + len(texts) :]) - head[1 + len(texts) :], head[1 + len(texts) :], strict=True) for a in range(s, s + n - 49)]
    assert sorted(at) == every


def test_empty_and_null_ids(spark):
    df = spark.createDataFrame([(None, "z" * 80), (1, "z" * 80), (1, "z" * 80)], "doc_id long, text string")
    got = sorted((r.doc_id is None, r.n_removed) for r in sd.suffix_dedup(df).collect())
    assert got == [(False, 0), (False, 0), (True, 80)]
    assert sd.suffix_dedup(df.limit(0)).count() == 0


def test_multikey_order(monkeypatch):
    rng = np.random.default_rng(0)
    monkeypatch.setattr(sd, "SMALL_SORT", 8)
    for n, most in ((300, 4), (1000, 2), (500, 1 << 60), (40, 1), (0, 1)):
        keys = [rng.integers(0, most, n).astype(np.uint64) for _ in range(4)]
        order = sd.multikey_order(keys)
        rows = list(zip(*(k[order].tolist() for k in keys), strict=True))
        assert rows == sorted(rows) and sorted(order.tolist()) == list(range(n))


def test_suffixes_come_in_the_order_of_their_bytes():
    """The first three words of the sort keys are the suffix's first 20 bytes."""
    texts = [(t or "").encode() for _, t in corpus(6)]
    head = np.concatenate([[len(texts)], np.arange(len(texts)), [len(t) for t in texts]]).astype(np.int64)
    chunk = sd.Chunk(zstandard.compress(head.tobytes() + b"".join(texts)), 50)
    starts = np.concatenate([s.start for s in chunk.slices()])
    keys, doc, _, _ = chunk.anchors()
    data = chunk.data.tobytes()
    order = sd.multikey_order(keys[:3])
    grams = [data[s : s + 20] for s in starts[order].tolist()]
    assert grams == sorted(grams) and len(grams) > 100
    words = [int(a).to_bytes(8, "big") + int(b).to_bytes(8, "big") + int(c).to_bytes(4, "big") for a, b, c in zip(*(k[order] for k in keys[:3]), strict=True)]
    assert words == grams
