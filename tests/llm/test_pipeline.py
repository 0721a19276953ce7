import random

import corpus_pipeline
from test_decontaminate import brute as leaks
from test_quality import brute as measures
from test_simhash import brute_groups as groups

from glyphfold.llm import bin_packing, pii_crf
from glyphfold.session import settle


def test_stages_against_brute_force(spark, tmp_path):
    random.seed(9)
    vocab = [f"w{chr(97 + i % 26)}{chr(97 + i // 26)}" for i in range(400)]
    say = lambda k: " ".join(random.choices(vocab, k=k))
    items = [(i, say(30)) for i in range(5)]
    rows = [(i, say(random.choice([10, 80, 200, 1500])), "en", f"s{i % 3}", 1) for i in range(80)]
    rows += [(100, rows[2][1], "en", "s1", 1), (101, rows[3][1] + " end", None, None, None), (102, None, "en", "s1", 0), (103, "a b c " * 200, "en", "s1", 1)]
    rows += [(110 + i, f"{say(60)} {items[i][1]} {say(20)}", "en", "s2", 1) for i in range(3)]
    rows += [(120, say(70) + " me@example.com +1 (743) 555-3824 " + say(5), "en", "s2", 7)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")

    texts = {r[0]: r[1] for r in rows}
    want = set()
    for i, t in texts.items():
        n, _, _, _, repeats = measures(t)
        if n >= 50 and 100 * repeats <= 50 * n:
            want.add(i)
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    columns = docs.columns
    steps = []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = settle(stage(spark, docs, str(tmp_path)), name)
        assert docs.columns == columns
        steps.append({r.doc_id: r for r in docs.collect()})
    assert set(steps[0]) == want
    want = {i for i, r in groups([(i, texts[i]) for i in want]).items() if i == r}
    assert set(steps[1]) == want
    want -= {w[0] for w in leaks([(i, texts[i]) for i in want], items)}
    assert set(steps[2]) == want and not want & {110, 111, 112}
    assert set(steps[3]) == want
    assert "[EMAIL]" in steps[3][120].text and steps[3][120].n_chars == len(steps[3][120].text)
    out = corpus_pipeline.run(spark, str(tmp_path)).collect()
    encode = bin_packing.encoder(*bin_packing.public_paths())
    lengths = {}
    for r in out:
        lengths[r.doc_id] = lengths.get(r.doc_id, 0) + r.length
    field = pii_crf.default_field()
    for i in want:
        base, more = pii_crf.find_all([texts[i]], field)
        assert lengths[i] == len(encode(pii_crf.masked(texts[i], base[0] + more[0]))) + 1
    assert set(lengths) == want
