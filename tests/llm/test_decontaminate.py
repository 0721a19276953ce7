import random
import re
from collections import Counter

from glyphfold.llm import decontaminate as dc


def norm(text):
    return re.sub(r"[\x00-\x2f\x3a-\x40\x5b-\x60\x7b-\x7f]", " ", (text or "").lower()).split()


def grams(words):
    w = min(5, len(words))
    return Counter(tuple(words[i : i + w]) for i in range(len(words) - w + 1))


def brute(docs, items):
    out = {}
    for d, text in docs:
        words = norm(text)
        for i, item in items:
            own = norm(item)
            if not own:
                continue
            g = grams(own)
            for s in range(len(words) - len(own) + 1):
                h = grams(words[s : s + len(own)])
                j = sum((g & h).values()) / sum((g | h).values())
                if j >= 0.8 and (-j, s) < out.get((d, i), (0, 0)):
                    out[d, i] = (-j, s)
    return {(d, i, s, round(-j, 9)) for (d, i), (j, s) in out.items()}


def test_matches_brute_force(spark):
    random.seed(4)
    vocab = ["the", "of", "Été", "ab", "dont", "x1", "ing", "or"] + [f"w{i}" for i in range(40)]
    say = lambda k: " ".join(random.choices(vocab, k=k))
    items = [(i, say(random.randint(12, 60))) for i in range(25)] + [(30, None), (31, "..."), (32, "tiny item"), (33, "the the the the the the the")]
    items.append((34, items[0][1]))
    docs = [(0, None), (1, ""), (2, "The the, the the THE the the. the")]
    for k in range(70):
        w = random.choice(items)[1] or ""
        words = w.split()
        for _ in range(random.choice([0, 0, 1, 2])):
            if words:
                words[random.randrange(len(words))] = "changed"
        if random.random() < 0.3 and len(words) > 3:
            del words[random.randrange(len(words))]
        body = " ".join(words)
        body = body.upper() if k % 3 == 0 else body.replace(" ", ",\n", 2)
        docs.append((10 + k, f"{say(random.randint(0, 80))}. {body}! {say(random.randint(0, 80))}"))
    ddf = spark.createDataFrame([(a, b, "z") for a, b in docs], "doc_id long, text string, item_id string").repartition(3)
    idf = spark.createDataFrame(items, "item_id long, text string")
    want = brute(docs, items)
    got = {(r.doc_id, r.item_id, r.start_word, round(r.similarity, 9)) for r in dc.contaminated(ddf, idf).collect()}
    assert got == want and len(want) > 20
    some = {(r.doc_id, r.item_id, r.start_word, round(r.similarity, 9)) for r in dc.contaminated(ddf, idf, block_bytes=900).collect()}
    assert some == want
    bad = {w[0] for w in want}
    assert {r.doc_id for r in dc.decontaminate(ddf, idf).collect()} == {d for d, _ in docs} - bad
    assert dc.contaminated(ddf.limit(0), idf).count() == 0 and dc.contaminated(ddf, idf.limit(0)).count() == 0


def test_multi_index_finds_all_within_radius():
    random.seed(5)
    fps = [random.getrandbits(64) for _ in range(50)]
    index = dc.MultiIndex(6, fps)
    prints = []
    for f in fps:
        for b in random.sample(range(64), 6):
            f ^= 1 << b
        prints.append(f)
    found = list(zip(*(x.tolist() for x in index.within(dc.np.array(prints, dc.U))), strict=True))
    near = [(w, i, (p ^ f).bit_count()) for w, p in enumerate(prints) for i, f in enumerate(fps) if (p ^ f).bit_count() <= 6]
    assert found == near and {(i, i, 6) for i in range(50)} <= set(found)


def test_segments_give_the_same_windows(spark, monkeypatch):
    """Long texts, read in segments, with items across the cuts, give what they give as a whole."""
    random.seed(7)
    vocab = [f"w{k}" for k in range(60)]
    items = [(i, " ".join(random.choices(vocab, k=25 + i))) for i in range(8)]
    docs = [(k, " ".join(" ".join(random.choices(vocab, k=random.randint(5, 90))) + " " + random.choice(items)[1] for _ in range(12))) for k in range(6)]
    docs.append((9, " ".join([items[0][1]] * 300)))
    index = dc.Benchmark(items, 5, 0.8, 20)
    whole = [index.best_windows(t) for _, t in docs]
    monkeypatch.setattr(dc.Benchmark, "WORDS", 40)
    monkeypatch.setattr(dc.Benchmark, "WINDOWS", 7)
    cut = dc.segments
    monkeypatch.setattr(dc, "segments", lambda text, room, overlap: cut(text, room, overlap, 64))
    assert [index.best_windows(t) for _, t in docs] == whole and all(whole)


def test_rows_are_judged_one_by_one(spark):
    """Rows that share an id keep their own verdicts; columns of any name pass through."""
    item = " ".join(f"q{i}" for i in range(30))
    rows = [(1, f"some words {item} and more", "a"), (1, "clean text", "b"), (2, "clean text", "c"), (2, "clean text", "c"), (None, item, "d"), (None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, _gone string")
    got = dc.decontaminate(docs, spark.createDataFrame([(7, item)], "item_id long, text string"))
    assert got.columns == docs.columns
    assert sorted(map(str, map(tuple, got.collect()))) == sorted(map(str, [rows[1], rows[2], rows[3], rows[5]]))


def test_documents_shorter_than_an_item(spark):
    """An item without some of its words, as a whole document, is found as brute force finds it."""
    random.seed(6)
    items = [(i, " ".join(random.choices([f"w{k}" for k in range(80)], k=38 + i))) for i in range(6)]
    docs = []
    for i, text in items:
        words = text.split()
        docs += [(10 * i + k, " ".join(w)) for k, w in enumerate((words[:-1], words[2:], words[:-4], words[1:-1], words[:-12], words[:3]))]
    want = brute(docs, items)
    for d, text in docs:
        for i, item in items:
            a, b = norm(text), norm(item)
            if len(a) < len(b):
                g, h = grams(a), grams(b)
                j = sum((g & h).values()) / sum((g | h).values())
                if j >= 0.8:
                    want.add((d, i, 0, round(j, 9)))
    ddf = spark.createDataFrame(docs, "doc_id long, text string").repartition(2)
    idf = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id, r.start_word, round(r.similarity, 9)) for r in dc.contaminated(ddf, idf).collect()}
    assert got == want and len(want) >= 18
