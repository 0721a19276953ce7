import random

import numpy as np

from glyphfold.llm import cotraining as ct


def corpus(n=900):
    random.seed(8)
    vocab = [f"w{i}" for i in range(300)]
    rows, labels = [], []
    for i in range(n):
        words = random.choices(vocab, k=random.randint(20, 120))
        junk, toxic = random.random() < 0.3, random.random() < 0.2
        if junk:
            words = [w + random.choice(["###", "$$$", "!!"]) for w in words]
        if toxic:
            for _ in range(3):
                words.insert(random.randrange(len(words)), random.choice(["awful", "Vile,", "rotten"]))
        text = " ".join(words)
        rows.append((i, text, "en", "bad" if junk and random.random() < 0.8 else f"s{i % 9}", len(text)))
        if i % 2:
            labels.append((i, int(not junk), int(toxic)))
    return rows, labels


def frames(spark, rows, labels):
    return (
        spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(3),
        spark.createDataFrame(labels, "doc_id long, quality int, toxic int"),
    )


def test_held_out_accuracy(spark):
    rows, labels = corpus()
    docs, known = frames(spark, rows, labels)
    truth = {i: ("###" in t or "$$$" in t or "!!" in t, any(w in t for w in ("awful", "Vile", "rotten"))) for i, t, *_ in rows}
    got = {r.doc_id: r for r in ct.quality_scores(docs, known).collect()}
    assert sorted(got) == [r[0] for r in rows]
    unseen = [i for i in truth if i % 2 == 0]
    assert np.mean([(got[i].quality < 0.5) == truth[i][0] for i in unseen]) > 0.97
    assert np.mean([(got[i].toxic >= 0.5) == truth[i][1] for i in unseen]) > 0.97
    assert all(got[i].kept == (got[i].quality >= 0.5 and got[i].toxic < 0.5) for i in got)


def test_views_teach_each_other():
    """With few labels the pool helps: the text view learns words from what metadata is sure of."""
    rng = np.random.default_rng(3)
    y = rng.random(1500) < 0.5
    meta = np.column_stack([np.ones(1500), np.where(y, 1.0, -1.0) + rng.normal(0, 0.5, 1500)])
    words = [[f"{'p' if v else 'n'}{k}" for k in rng.integers(0, 60, 6)] + [f"c{k}" for k in rng.integers(0, 40, 6)] for v in y]
    labels = np.full((1500, 2), -1)
    labels[:80, 0] = y[:80]
    right = []
    for rounds in (0, 3):
        state = ct.CoTraining(words, meta, labels, least_z=-1)
        pool = np.arange(80, 1500)
        for _ in range(rounds):
            p = [ct.sigmoid(z[:, 0]) for z in state.model.views([state.all_ids[i] for i in pool], meta[pool])]
            for view in (0, 1):
                at = np.flatnonzero(np.abs(p[view] - 0.5) > 0.4)[:200]
                state.teach(0, view, [state.all_ids[pool[i]] for i in at], meta[pool[at]], (p[view][at] > 0.5).astype(float))
            state.fit()
        z = state.model.views([state.all_ids[i] for i in pool], meta[pool])[0][:, 0]
        right.append(np.mean((z > 0) == y[80:]))
    assert right[1] >= right[0] and right[1] > 0.85


def test_scores_and_exchange_match_brute_force(spark):
    """A round passes on what a loop over all unlabelled documents would; scores are those of whole texts."""
    rows, labels = corpus(500)
    rows += [(7, rows[7][1] + " twice", "en", None, None), (900, None, None, None, None)]
    docs, known = frames(spark, rows, labels)
    state = ct.start(docs, known)
    table = ct.numbered_texts(docs, state.model.vocab)
    pool = table.join(known.select("doc_id"), "doc_id", "left_anti")
    seen = ct._Seen()
    vocab = state.model.vocab

    def views(text, lang, source, n):
        ids = np.array(sorted(vocab[f] for f in ct.text_features(text, seen) | set(ct.layout_of(text or "")) if f in vocab), np.int64)
        return ids, np.array(ct.metadata(lang, source, n))

    quotas, had = state.quotas(40), {i for i, *_ in labels}
    want = {}
    for t, view, label in quotas:
        found = []
        for i, *rest in rows:
            ids, meta = views(*rest)
            z = state.model.text[ids, t].sum() + state.model.text_offset[t] if view == 0 else meta @ state.model.meta[:, t] + state.model.meta_offset[t]
            p = ct.sigmoid(z)
            if i not in had and (p if label else 1 - p) > 0.9:
                found.append((ct.draws_of([i])[0], i))
        want[t, view, label] = {i for _, i in sorted(set(found))[: quotas[t, view, label]]}
    taken = ct.defaultdict(set)
    ct.exchange(state, pool, 40, taken)
    assert {k: taken[k] for k in ((0, 0), (0, 1), (1, 0), (1, 1))} == {(t, v): want[t, v, 0] | want[t, v, 1] for t in (0, 1) for v in (0, 1)}
    state.fit()
    model = state.finish()
    got = sorted((r.doc_id, round(r.quality, 9), round(r.toxic, 9)) for r in ct.quality_scores(docs, known, model).collect())
    brute = []
    for i, *rest in rows:
        ids, meta = views(*rest)
        z = (model.text[ids].sum(axis=0) + model.text_offset) * model.mix[:, 0] + (meta @ model.meta + model.meta_offset) * model.mix[:, 1] + model.mix[:, 2]
        brute.append((i, *(round(float(x), 9) for x in ct.sigmoid(z))))
    assert got == sorted(brute)


def test_views_are_apart():
    """The metadata view never sees the text, the text view nothing else."""
    assert ct.metadata("en", "s", 10) == ct.metadata("en", "s", 10) and len(ct.metadata(None, None, None)) == ct.N_META
    assert ct.metadata.__code__.co_varnames[:3] == ("lang", "source", "n_chars")
    assert ct.layout_of("") == ct.layout_of("") and ct.text_features(None, ct._Seen()) == set()


def test_edge_cases(spark):
    docs, known = frames(spark, [(1, None, None, None, None), (2, "", "", "", 0), (3, "x " * 50000, "en", "s", 5)], [(1, 1, 0)])
    for r in ct.quality_scores(docs, known).collect():
        assert (r.quality, r.toxic, r.kept) == (1.0, 0.0, True)
    assert {r.kept for r in ct.quality_scores(docs, known.limit(0)).collect()} == {True}
    assert ct.quality_scores(docs.limit(0), known).count() == 0
