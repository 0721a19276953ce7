import hashlib
import re

from glyphfold.llm import pii_crf as pc

CASES = [
    None, "", "no data here", "a@b.c", "x..y%+@a-b.c.d. z@q w@e.", "a@b@c.d e@f.g@h.i", "@a.b", "é@x.y", "1.2.3.4", "256.1.1.1 1.2.3.4.5.6.7.8.9", "0001.2.3.004 1.2.3",
    "4111 1111 1111 1111", "4111-1111 1111 1112", "4785380592391139$$$", "12  34 5-6", "+1 (743) 555-3824, +12 3 ", "++1 2345 67890 (", "+123456789012345678 +1-2-3-4-5-6-7-8-9-0 x",
    "tel +1 (310) 555-4510 and 5.6.7.8 at q.w@mail1.example.com token = \"24be64439e3e49cf46b2d7c90f3602a3d0b907ff\" end",
    "a" * 5000 + "@" + "b." * 2000, "1" * 5000, "1." * 3000, "+1" + " " * 4000, "٣٤٥٦ ١.٢.٣.٤",
]


def brute(text):
    """The patterns as they are written."""
    text = text or ""
    digits = lambda s: re.sub("[^0-9]", "", s)
    kinds = {
        "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda s: True),
        "ip": (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda s: all(int(x) <= 255 for x in s.split("."))),
        "card": (r"[0-9]([\x20-]?[0-9])+", lambda s: 13 <= len(digits(s)) <= 19 and sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(digits(s)[::-1])) % 10 == 0),
        "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", lambda s: 9 <= len(digits(s)) <= 15),
    }
    return [f"{k}:{m.start()}:{m.end()}" for k, (p, ok) in kinds.items() for m in re.finditer(p, text) if len(m[0]) < 4000 and ok(m[0])]


def test_base_matches_the_patterns():
    for t in CASES:
        assert [f"{k}:{a}:{b}" for k, a, b in pc.base_spans(t or "") if b - a < 4000] == brute(t), t and t[:60]


def test_field_learns_its_table_and_generalises():
    field = pc.default_field()
    rows = pc.labelled_rows()
    paths = field.decode([t for t, _ in rows])
    right = sum(p == y for path, (_, labels) in zip(paths, rows, strict=True) for p, y in zip(path, labels, strict=True))
    assert right / sum(len(y) for _, y in rows) > 0.98
    new = {
        'then token = "0123456789abcdef0123456789abcdef01234567" ends': ["secret"],
        "call 212-555-0147 after lunch": ["phone"],
        "she was born in 1999 on page 7": [],
        "nothing 12 apples and 30 pears": [],
    }
    for text, kinds in new.items():
        base, more = pc.find_all([text], field)
        assert [k for k, _, _ in base[0] + more[0]] == kinds, (text, more)


def test_viterbi_is_optimal():
    import itertools

    import numpy as np

    rng = np.random.default_rng(0)
    k = pc.Field.labels
    f = pc.Field({}, np.zeros((0, k)), rng.normal(size=(k + 1, k)))
    scores = rng.normal(size=(3, 3, k))
    lens = np.array([3, 2, 1])
    f.scores = lambda segs: (scores, lens)
    for i, path in enumerate(f.decode([["a"]] * 3)):
        value = lambda y: f.move[k, y[0]] + sum(scores[i, j, v] for j, v in enumerate(y)) + sum(f.move[a, b] for a, b in zip(y, y[1:]))  # noqa: B023,B905,E731
        assert abs(value(path) - max(map(value, itertools.product(range(k), repeat=int(lens[i]))))) < 1e-9


def test_query_and_redaction(spark):
    df = spark.createDataFrame([(i, t, 5, "x") for i, t in enumerate(CASES)], "doc_id long, text string, n_chars long, spans string").repartition(2)
    for r in pc.personal_data(df).collect():
        want = [f"{k}:{a}:{b}" for k, a, b in pc.base_spans(CASES[r.doc_id] or "")]
        assert r.base_sha256 == hashlib.sha256(",".join(want).encode()).hexdigest()
        assert set(want) <= set(r.spans.split(",")) | {""}
        assert r.n_email == sum(w.startswith("email") for w in want)
    out = {r.doc_id: r for r in pc.redact(df).collect()}
    assert out[0].text is None and out[0].n_chars == 5 and out[2].text == "no data here"
    assert out[18].text == 'tel [PHONE] and [IP] at [EMAIL] token = "[SECRET]" end'
    assert out[18].n_chars == len(out[18].text) and out[3].spans == "x"
    assert pc.personal_data(df.limit(0)).count() == 0


def test_spans_without_digit_or_at_sign():
    field = pc.default_field()
    cases = {
        "contact us at sales (at) widgets dot example dot com any time": ("email", "sales (at) widgets dot example dot com"),
        "write to help [at] acme dot org today": ("email", "help [at] acme dot org"),
        "then password=correcthorsebattery do not share": ("secret", "correcthorsebattery"),
        'set token = "abcdefghijklmnopqrst" in shell': ("secret", "abcdefghijklmnopqrst"),
        "api_key: qwertyuiopasdfghjkl keep it safe": ("secret", "qwertyuiopasdfghjkl"),
    }
    for text, (kind, part) in cases.items():
        base, more = pc.find_all([text], field)
        assert [(k, text[a:b]) for k, a, b in more[0]] == [(kind, part)], (text, more)
    for text in ("the password is needed by all", "a key token of the secret life", "look at the dot on the wall", "x = y in the sum"):
        assert pc.find_all([text], field) == ([[]], [[]]), text
