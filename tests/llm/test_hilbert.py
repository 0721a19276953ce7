import itertools
import zlib

import numpy as np

from glyphfold.llm import hilbert_shards as hs


def test_curve_is_a_walk_through_all_cells():
    for dims, bits in ((2, 3), (3, 2)):
        cells = np.array(list(itertools.product(range(1 << bits), repeat=dims)))
        at = hs.hilbert_index(cells, bits)
        assert sorted(at) == list(range(len(cells)))
        path = cells[np.argsort(at)]
        assert (np.abs(np.diff(path, axis=0)).sum(axis=1) == 1).all()


def test_rows_law(spark):
    rows = [(i, None if i % 11 == 0 else f"té{i % 17}" * (i % 5), "en" if i % 3 else None, f"s{i % 4}", i) for i in range(203)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, rank long")
    out = hs.hilbert_shards(df).collect()
    text = {r[0]: r[1] or "" for r in rows}
    assert sorted(r.doc_id for r in out) == list(range(203))
    by = {}
    for r in out:
        b = text[r.doc_id].encode()
        assert r["size"] == len(b) + 16 and r.text_crc32 == zlib.crc32(b)
        by.setdefault(r["shard"], []).append(r.slot)
    assert sorted(by) == list(range(40))
    assert all(sorted(s) == list(range(len(s))) for s in by.values())
    assert {len(s) for s in by.values()} <= {5, 6}
    assert hs.hilbert_shards(df.limit(0)).count() == 0
    assert sorted((r["shard"], r.slot) for r in hs.hilbert_shards(df.limit(3)).collect()) == [(0, 0), (1, 0), (2, 0)]
