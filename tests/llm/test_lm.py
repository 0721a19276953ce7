import math
import random
import re
import zlib
from collections import Counter

import numpy as np

from glyphfold.llm import interpolated_lm as lm


def tokens(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    return [*re.findall(r"[^\x20\x09-\x0D]+", low), "\n"]


def corpus():
    random.seed(6)
    vocab = ["the", "Of", "é", "a", "b."] + [f"w{i}" for i in range(60)]
    texts = [None, "", " \n", "THE the The"]
    for _ in range(150):
        w, text = "the", []
        for _ in range(random.randint(1, 60)):
            w = vocab[(hash_of(w) + random.choice([0, 0, 0, 1, random.randint(0, 64)])) % len(vocab)]
            text.append(w)
        texts.append(" ".join(text))
    return list(enumerate(texts)) + [(4, texts[4])]


def hash_of(w):
    return zlib.crc32(w.encode())


def brute(rows):
    fold = lambda i: zlib.crc32(str(i).encode()) % 7
    words, pairs, kept_words, kept_pairs = Counter(), Counter(), Counter(), Counter()
    docs = kept_docs = 0
    for i, t in rows:
        if fold(i) == 2:
            continue
        ts = tokens(t)
        prs = list(zip(["\r", *ts], ts))  # noqa: B905
        words.update(ts), pairs.update(prs)
        docs += 1
        if fold(i) != 3:
            kept_words.update(ts), kept_pairs.update(prs)
            kept_docs += 1
    n, v = words.total(), len(words)
    kn, kv = kept_words.total(), len(kept_words)
    cells = Counter()
    for i, t in rows:
        if fold(i) == 3:
            ts = tokens(t)
            for a, b in zip(["\r", *ts], ts):  # noqa: B905
                ch = kept_docs if a == "\r" else kept_words[a]
                one = lambda x: int(lm.binned(np.array([x]))[0])
                cells[(int(lm.context_bucket(np.array([ch]))[0]) * lm.BINS + one(kept_pairs[a, b] / max(ch, 1))) * lm.BINS + one(kept_words[b] / kn)] += 1
    mix = lm.learn(np.array(sorted(cells)), np.array([float(cells[c]) for c in sorted(cells)]), kv)
    out = []
    for i, t in rows:
        ts = tokens(t)
        base = sum(math.log10((words[w] + 1) / (n + v + 1)) for w in ts)
        score = 0
        for a, b in zip(["\r", *ts], ts):  # noqa: B905
            ch = docs if a == "\r" else words[a]
            w = mix[int(lm.context_bucket(np.array([ch]))[0])]
            score += math.log10(w[0] * pairs[a, b] / max(ch, 1) + w[1] * words[b] / n + w[2] / (v + 1))
        out.append((i, fold(i) == 2, len(ts), sum(words[w] > 0 for w in ts), n, round(base, 7), round(score, 7)))
    return sorted(out)


def test_matches_brute_force(spark, monkeypatch):
    rows = corpus()
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, score string").repartition(3)
    for size in (4 << 20, 900):
        monkeypatch.setattr(lm, "CHUNK_BYTES", size)
        got = sorted((*r[:5], round(r.base_score, 7), round(r.score, 7)) for r in lm.lm_scores(df).collect())
        assert got == brute(rows)
    held = [r for r in got if r[1]]
    assert sum(r[6] for r in held) > sum(r[5] for r in held)  # pairs help on text it has not seen
    assert lm.lm_scores(df.limit(0)).count() == 0


def test_probabilities_sum_to_at_most_one():
    mix = lm.learn(np.array([(3 * lm.BINS + 2) * lm.BINS + 5, lm.BINS * lm.BINS * 5]), np.array([3.0, 1.0]), 10)
    assert np.allclose(mix.sum(axis=1), 1)
