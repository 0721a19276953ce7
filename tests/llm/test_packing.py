import itertools
import random
import zlib

import numpy as np

from glyphfold.llm import bin_packing as bp


def test_fullest_is_optimal():
    random.seed(1)
    for _ in range(200):
        items = [random.randint(1, 12) for _ in range(random.randint(1, 8))]
        room = random.randint(1, 30)
        counts = {k: items.count(k) for k in set(items)}
        best = max(s for n in range(len(items) + 1) for c in itertools.combinations(items, n) if (s := sum(c)) <= room)
        used = bp.fullest(counts, room)
        assert sum(k * u for k, u in used.items()) == best
        assert all(u <= counts[k] for k, u in used.items())


def test_cut():
    assert bp.cut(1, 4) == [(0, 1)] and bp.cut(4, 4) == [(0, 4)] and bp.cut(9, 4) == [(0, 1), (1, 4), (5, 4)]


def test_encoders_agree():
    e = bp.encoder(*bp.public_paths())
    random.seed(2)
    letters = [chr(c) for c in range(0x250)]
    for _ in range(1500):
        t = "".join(random.choices(letters if random.random() < 0.5 else "ab  \n\t'sd9é \x85!", k=random.randint(0, 40)))
        assert e.fast.encode_ordinary(t) == e.reference.encode(t, add_special_tokens=False).ids, repr(t)
    assert e("a<|endoftext|>") == e.reference.encode("a<|endoftext|>", add_special_tokens=False).ids


def test_pack_round_trip(spark):
    random.seed(3)
    texts = [None, "", "x", "word " * 5000] + ["w é " * random.randint(0, 900) for _ in range(150)] + ["same text " * 300] * 60
    df = spark.createDataFrame([(i, t, i) for i, t in enumerate(texts)], "doc_id long, text string, rank long").repartition(3)
    path, ranks = bp.public_paths()
    rows = bp.pack(df, path, ranks).collect()
    e = bp.encoder(path, ranks)
    docs, bins = {}, {}
    for r in rows:
        docs.setdefault(r.doc_id, []).append(r)
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert set(docs) == set(range(len(texts)))
    for i, t in enumerate(texts):
        ids = e.reference.encode(t or "", add_special_tokens=False).ids + [2]
        at = 0
        for k, r in enumerate(sorted(docs[i], key=lambda r: r.piece)):
            assert (r.piece, r.start) == (k, at)
            assert r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(ids)
    for b in bins.values():
        at = 0
        for o, n in sorted(b):
            assert o == at
            at += n
        assert at <= 1024
    least = max(-(-sum(r.length for r in rows) // 1024), sum(r.length > 512 for r in rows))
    assert len(bins) <= 1.05 * least + 1
    assert bp.pack(df.limit(0), path, ranks).count() == 0
