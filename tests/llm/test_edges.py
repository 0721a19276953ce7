"""Every operator on one nasty table: nulls, empty and very long texts, repeated rows, clashing columns, no rows."""

import zlib

import corpus_pipeline
import pytest

from glyphfold.llm import bin_packing, cotraining, decontaminate, hilbert_shards, interpolated_lm, pii_crf, quality_rules, simhash_dedup, suffix_dedup, url_filter

ITEM = " ".join(f"item{i}" for i in range(30))
LONG = " ".join(f"word{i % 5000}" for i in range(300_000))  # some 3 MB
GOOD = " ".join(f"good{i}" for i in range(80))
ROWS = [
    (1, GOOD, "en", "s", 5), (1, "other text of the same id", "en", "s", 5), (2, GOOD, "en", None, 5), (2, GOOD, "en", None, 5), (3, None, None, None, None), (4, "", "", "", 0),
    (None, None, None, "s", 1), (None, GOOD + " tail", "en", "s", 1), (6, LONG, "en", "s", 7), (7, f"{GOOD} {ITEM} {GOOD}", "de", "t", 2), (8, "me@example.com " + GOOD, "en", "s", 1),
]
CLASH = ("row", "id", "key", "label", "host", "base_failed", "_gone", "chunk", "bucket", "fp", "space", "words", "copy", "rank", "length")


@pytest.fixture(scope="module")
def docs(spark):
    df = spark.createDataFrame(ROWS, "doc_id long, text string, lang string, source string, n_chars long")
    for c in CLASH:
        df = df.selectExpr("*", f"'x' as `{c}`")
    return df.repartition(3)


def ids(rows):
    return sorted((r.doc_id is None, r.doc_id or 0) for r in rows)


EVERY = sorted((r[0] is None, r[0] or 0) for r in ROWS)


def test_suffix_dedup(docs):
    got = suffix_dedup.suffix_dedup(docs, with_text=False).collect()
    assert ids(got) == EVERY
    assert sorted(r.n_removed for r in got if r.doc_id == 2) == [len(GOOD)] * 2 and all(r.n_removed == 0 for r in got if r.doc_id in (1, 3, 4))
    assert suffix_dedup.suffix_dedup(docs.limit(0)).count() == 0


def test_quality_rules(docs):
    got = quality_rules.quality_verdicts(docs).collect()
    assert ids(got) == EVERY and next(r.n_words for r in got if r.doc_id == 6) == 300_000
    assert all(r.base_failed for r in got if r.doc_id in (3, 4)) and quality_rules.quality_verdicts(docs.limit(0)).count() == 0


def test_url_filter(spark, docs):
    pages = docs.selectExpr("doc_id as page_id", "case when doc_id = 6 then concat('http://a.com/', text) else text end as url", *(f"`{c}`" for c in CLASH))
    labels = spark.createDataFrame([(1, 0, 1), (1, 1, 0), (None, 0, 0), (6, None, None)], "doc_id long, quality int, toxic int")
    got = url_filter.url_verdicts(pages, labels).collect()
    assert len(got) == len(ROWS) and {r.verdict for r in got} == {"allow"}


def test_cotraining(spark, docs):
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(9)] + [(None, 1, 1)], "doc_id long, quality int, toxic int")
    assert ids(cotraining.quality_scores(docs, labels).collect()) == EVERY


def test_decontaminate(spark, docs):
    items = spark.createDataFrame([(1, ITEM), (1, ITEM), (2, None), (None, "")], "item_id long, text string")
    assert {(r.doc_id, r.item_id) for r in decontaminate.contaminated(docs, items).collect()} == {(7, 1)}
    out = decontaminate.decontaminate(docs, items)
    assert out.columns == docs.columns and out.count() == len(ROWS) - 1


def test_personal_data(docs):
    got = pii_crf.personal_data(docs).collect()
    assert ids(got) == EVERY and {r.doc_id for r in got if r.n_email} == {8}
    out = pii_crf.redact(docs)
    assert out.columns == docs.columns and out.where("text like '%[EMAIL]%'").count() == 1


def test_many_spans_cost_their_number(docs):
    """Twice the spans take about twice the time, not four times."""
    import time

    field, took = pii_crf.default_field(), []
    for n in (1500, 6000):
        text = "\n".join(f"call +1 (743) 555-{i % 10000:04d} or 743.555.{i % 10000:04d} now" for i in range(n))
        began = time.process_time()
        base, more = pii_crf.find_all([text], field)
        took.append(time.process_time() - began)
        assert len(base[0]) == n
    assert took[1] < 8 * took[0]


def test_interpolated_lm(docs):
    got = interpolated_lm.lm_scores(docs).collect()
    assert ids(got) == EVERY and next(r.n_tokens for r in got if r.doc_id == 6) == 300_001
    assert len({(r.base_score, r.score) for r in got if r.doc_id == 2}) == 1 and {r.n_tokens for r in got if r.doc_id in (3, 4)} == {1}
    assert interpolated_lm.lm_scores(docs.limit(0)).count() == 0


def test_packing(docs):
    got = bin_packing.pack(docs, *bin_packing.public_paths()).collect()
    starts = [r for r in got if r.piece == 0]
    assert ids(starts) == EVERY and all(r.length <= 1024 for r in got)


def test_near_dedup(docs):
    out = simhash_dedup.near_dedup(docs)
    assert out.columns == docs.columns
    assert ids(out.collect()) == sorted([(False, 1), (False, 1), (False, 3), (False, 6), (False, 7)])
    got = simhash_dedup.simhash_components(docs).collect()
    assert ids(got) == EVERY and len({r.fp for r in got if r.doc_id in (3, 4)}) == 1


def test_shards_match_brute_force(docs):
    """The curve's order, cut into runs, by a plain sort of all rows."""
    got = hilbert_shards.hilbert_shards(docs, shards=4).collect()
    assert ids(got) == EVERY
    order = sorted(got, key=lambda r: (r.shard, r.slot))
    assert [r.curve for r in order] == sorted(r.curve for r in got)
    n, base, more = len(got), *divmod(len(got), 4)
    assert [r.shard for r in order] == [k for k in range(4) for _ in range(base + (k < more))]
    assert all([r.slot for r in order if r.shard == k] == list(range(base + (k < more))) for k in range(4)) and n == len(ROWS)
    texts = {(i, len((t or "").encode()) + 16, zlib.crc32((t or "").encode())) for i, t, *_ in ROWS}
    assert {(r.doc_id, r.size, r.text_crc32) for r in got} == texts


def test_pipeline_runs(spark, docs, tmp_path):
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, ITEM)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert {r.doc_id for r in got} <= {1, 6, 8}
    docs.limit(0).write.parquet(f"{tmp_path}/none/documents.parquet")
    spark.createDataFrame([], "item_id long, text string").write.parquet(f"{tmp_path}/none/benchmark.parquet")
    assert corpus_pipeline.run(spark, f"{tmp_path}/none").count() == 0
