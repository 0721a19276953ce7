import random
import re

import numpy as np
import xxhash

from glyphfold.llm import simhash_dedup as sd


def brute_print(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    ones = [0] * 64
    for s in shingles:
        h = xxhash.xxh64_intdigest(s.encode(), 42)
        for b in range(64):
            ones[b] += h >> b & 1
    return sum(1 << b for b in range(64) if 2 * ones[b] > len(shingles))


def brute_roots(fps):
    root = dict.fromkeys(fps)
    ids = sorted(fps)
    for i in ids:
        if root[i] is None:
            todo, root[i] = [i], i
            while todo:
                a = todo.pop()
                for b in ids:
                    if root[b] is None and bin(fps[a] ^ fps[b]).count("1") <= 3:
                        root[b] = i
                        todo.append(b)
    return root


def test_covering_code_reaches_every_pair():
    rng = np.random.default_rng(1)
    half = rng.integers(0, 2**32, 300, dtype=np.uint32)
    for flip in [0, *[1 << b for b in range(32)]]:
        home, _, _ = sd.anchors(half)
        other = half ^ np.uint32(flip)
        _, rows, near = sd.anchors(other)
        reach = {(int(r), int(a)) for r, a in zip(rows, near, strict=True)}
        assert all((i, int(home[i])) in reach for i in range(len(half)))


def test_components_match_brute_force(spark, monkeypatch):
    random.seed(3)
    vocab = ["aa", "Bb", "ccc", "dé", "e", "ff,", "gg", "hh", "iii", "jj"]
    texts = [None, "", "  ", "one", "one two", "X" * 3000]
    texts += [" ".join(random.choices(vocab, k=random.randint(3, 80))) for _ in range(60)]
    long = random.choices(vocab, k=900)
    for _ in range(40):
        w = list(long)
        for _ in range(random.randint(0, 3)):
            w[random.randrange(len(w))] = random.choice(vocab)
        texts.append(" ".join(w))
    texts += texts[3:9]
    rows = list(enumerate(texts))
    random.shuffle(rows)
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, fp string").repartition(3)
    fps = {i: brute_print(t) for i, t in rows}
    want = {i: (f"{fps[i]:016x}", r) for i, r in brute_roots(fps).items()}
    for hot in (256, 1):
        monkeypatch.setattr(sd, "HOT_ANCHOR", hot)
        got = {r.doc_id: (f"{r.fp % 2**64:016x}", r.component_id) for r in sd.simhash_components(df).collect()}
        assert got == want
    assert sd.simhash_components(df.limit(0)).count() == 0


def test_chain_of_prints(spark):
    fps, x = [], 0
    for i in range(20):
        fps.append((i + 5, x))
        x ^= 0b111 << (3 * i)
    df = spark.createDataFrame([(i, np.uint64(f).astype(np.int64).item()) for i, f in fps], "id long, fp long")
    from glyphfold.operators.components import connected_components

    roots = {r.id: r.root for r in connected_components(sd.links(df)).collect()}
    assert set(roots.values()) == {5} and len(roots) == 20


def test_anchors_hot_at_every_level(spark, monkeypatch):
    """Anchors split again and again still bring linked fingerprints together."""
    from glyphfold.operators.components import connected_components

    monkeypatch.setattr(sd, "HOT_ANCHOR", 0)
    fps = [0, 0b111 << 40, (0b111 << 40) | (1 << 33 | 1 << 3 | 1 << 60), 0xF0F0F0F0]
    df = spark.createDataFrame([(i, f) for i, f in enumerate(fps)], "id long, fp long")
    roots = {r.id: r.root for r in connected_components(sd.links(df)).collect()}
    assert roots == {0: 0, 1: 0, 2: 0}


def brute_groups(docs, similarity=0.8):
    """Smallest id of each document's group: documents linked by similarity of their five-word shingles."""
    sets = {i: set(sd.shingle_hashes(t, 5)) for i, t in docs}
    root, ids = {}, sorted(sets)
    for i in ids:
        if i in root:
            continue
        root[i], todo = i, [i]
        while todo:
            a = todo.pop()
            for b in ids:
                if b not in root and len(sets[a] & sets[b]) >= similarity * len(sets[a] | sets[b]):
                    root[b] = i
                    todo.append(b)
    return root


def test_near_copies_make_groups(spark, monkeypatch):
    """Groups of near copies, also by chains, keep their smallest document; others stay."""
    random.seed(11)
    vocab = ["the", "of", "and"] + [f"{a}{b}word{i}" for i, (a, b) in enumerate((x, y) for x in "abcdefghij" for y in "klmnopqrst")]
    docs = []
    for base in range(25):
        words = random.choices(vocab, k=random.randint(150, 500))
        for copy in range(random.randint(1, 6)):
            w = list(words)
            for _ in range(0 if copy == 0 else random.randint(0, len(w) // 60)):
                w[random.randrange(len(w))] = random.choice(vocab)
            docs.append((len(docs), " ".join(w).upper() if copy == 1 else " ".join(w)))
    for base in range(4):  # chains: only neighbours are alike
        words = random.choices(vocab, k=120)
        for step in range(8):
            docs.append((len(docs), " ".join(words)))
            words = words[6:] + random.choices(vocab, k=6)
    random.shuffle(docs)
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    want = {i: r for i, r in brute_groups(docs).items() if i != r}
    assert len(want) > 50
    for room in (1000, 2):  # with buckets as a whole, and dealt out in blocks
        monkeypatch.setattr(sd, "BUCKET_TEXTS", room)
        assert {r.id: r.kept for r in sd.near_duplicates(df).collect()} == want
    assert sd.near_dedup(df.limit(0)).count() == 0


def test_scattered_edits_are_found(spark):
    """Copies with edits spread over short words, near the bound: all are found."""
    random.seed(12)
    vocab = [f"{a}{b}{c}" for a in "bcdfg" for b in "aeiou" for c in "klmnp"]
    docs = []
    for base in range(60):
        words = random.choices(vocab, k=200)
        docs.append((2 * base, " ".join(words)))
        for at in range(10 + base, 200, 50):
            words[at] = "edit"
        docs.append((2 * base + 1, " ".join(words)))
    sets = {i: set(sd.shingle_hashes(t, 5)) for i, t in docs}
    j = lambda a, b: len(sets[a] & sets[b]) / len(sets[a] | sets[b])
    due = {i: i - 1 for i in sets if i % 2 and j(i, i - 1) >= 0.8}
    assert len(due) > 50 and all(j(i, k) < 0.9 for i, k in due.items())
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    assert {r.id: r.kept for r in sd.near_duplicates(df).collect()} == due


def test_one_key_for_many_groups(spark, monkeypatch):
    """Many groups of near copies under one key: every one is brought down to its smallest document."""
    random.seed(13)
    docs = []
    for base in range(12):
        words = [f"w{base}x{i}" for i in range(120)]
        for copy in range(3):
            docs.append((base + 12 * copy, " ".join(words + [f"tail{copy}"])))
    one_key = sd.band_batches

    def chained(*args):
        for b in one_key(*args):
            yield b.set_column(3, "keys", sd.pa.array([[7]] * len(b), sd.pa.list_(sd.pa.int64())))

    monkeypatch.setattr(sd, "band_batches", chained)
    monkeypatch.setattr(sd, "BUCKET_TEXTS", 5)
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    gone = {r.id: r.kept for r in sd.near_duplicates(df).collect()}
    assert gone == {i: i % 12 for i, _ in docs if i >= 12}


def test_rows_are_judged_one_by_one(spark):
    """Rows that share an id keep their own verdicts; of rows repeated as a whole one stays; nulls come last."""
    say = lambda k: " ".join(f"{k}w{i}" for i in range(60))
    rows = [(1, say("a"), "x", 0), (1, say("b"), "x", 0), (2, say("a"), "x", 0), (3, say("a") + " end", "x", 0), (3, say("c"), "x", 0)]
    rows += [(4, say("d"), "y", 1), (4, say("d"), "y", 1), (None, say("d"), "y", 1), (None, say("e"), "z", 1), (5, None, None, 1), (6, " ", None, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, _gone string, id long").repartition(3)
    out = sd.near_dedup(docs)
    assert out.columns == docs.columns
    want = [rows[0], rows[1], rows[4], rows[5], rows[8], rows[9]]
    assert sorted(map(str, map(tuple, out.collect()))) == sorted(map(str, want))
    assert sd.near_dedup(docs.limit(0)).count() == 0
    assert sorted((r.id, r.kept) for r in sd.near_duplicates(docs.where("doc_id > 1")).collect()) == [(3, 2), (4, 4), (6, 5)]


def test_stage_groups_by_fingerprints(spark, monkeypatch):
    """Groups come through linked fingerprints, also where no key of minima is shared; unlike texts of one component stay apart."""
    random.seed(14)
    docs = []
    for base in range(10):
        words = [f"w{base}x{i}" for i in range(2000)]
        for copy in range(3):
            docs.append((base + 10 * copy, " ".join(words + [f"tail{copy}"])))
    fps = {i: sd.fold_bits(np.array(sd.shingle_hashes(t), np.uint64), np.array([len(sd.shingle_hashes(t))]))[0] for i, t in docs}
    due = {i: i % 10 for i, _ in docs if i >= 10 and bin(int(fps[i] ^ fps[i % 10])).count("1") <= 3}
    assert len(due) > 15
    whole = sd.band_batches
    arrow = sd.pa
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)

    def own_keys(*args):
        for b in whole(*args):
            yield b.set_column(3, "keys", arrow.array([[x] for x in b.column("id").to_pylist()], arrow.list_(arrow.int64())))

    def one_print(*args):
        for b in own_keys(*args):
            yield b.set_column(4, "fp", arrow.array([5] * len(b), arrow.int64()))

    monkeypatch.setattr(sd, "band_batches", own_keys)
    gone = {r.id: r.kept for r in sd.near_duplicates(df).collect()}
    assert gone.items() >= due.items() and all(i % 10 == kept % 10 for i, kept in gone.items())
    monkeypatch.setattr(sd, "band_batches", one_print)
    assert {r.id: r.kept for r in sd.near_duplicates(df).collect()} == {i: i % 10 for i, _ in docs if i >= 10}
