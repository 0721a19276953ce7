"""Personal data: fixed patterns, and a linear-chain conditional random field.

The patterns find e-mail addresses, IP addresses, card and phone numbers exactly as
specified; each is anchored at a character it must hold, so no text takes quadratic
time. The random field adds what they miss (numbers in other notations, spelled-out
addresses, secrets): it labels the tokens around every digit, at-sign, spelled-out
at or dot, and word or sign that announces a secret, from features of word shape and of neighbours, is trained from a small labelled table by
gradient ascent on the exact likelihood, and decodes batches of segments by Viterbi
in numpy. Found spans stay when they don't overlap one of the patterns.

Addresses, cards and phones in figures hold a digit or an at-sign; e-mail addresses
and secrets may hold neither. Text without any of these signs needs no decoding. Positions are code points.

Defined cases: null and empty texts have no spans; a null id is carried; repeated rows are
judged alike; of added spans that overlap the first one stays; very long texts cost their
own length and are held by one task; an empty table gives no rows; other columns pass
through or play no part, whatever their names.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KINDS = ("email", "ip", "card", "phone", "secret")
BASE = KINDS[:4]
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
MARK = re.compile("[0-9@]")
DIGIT = re.compile("[0-9]")
#: What else starts decoding: spelled-out addresses, and what announces a secret.
CUE = re.compile(
    r"[0-9@]|[\[({<]\s*at\s*[\])}>]|(?<![A-Za-z])(?:dot|pass(?:word|wd|phrase)|pwd|token|secret|bearer)(?![a-z])|(?<![A-Za-z])(?:api|aws|access|private)?[_ -]?key\s*[=:\"']|=", re.IGNORECASE
)

#: A small labelled table: spans are marked as [kind text].
LABELLED = """
please write to [email jane.doe@example.org] for details
contact us at [email sales (at) widgets dot example dot com] any time1
mail [email bob99 [at] example.net] or come by
send it to [email info@localhost] today
reach me under [email first.last @ example.com] soon
my address is [email x_y@mail.example.co.uk] thanks
or by mail: [email a.b+c@sub.example.com].
call me at [phone 555-123-4567] tomorrow
phone: [phone (310) 555-0199] ext none
tel. [phone 020 7946 0958] in the evening
fax [phone 030/1234567] office
ring [phone +1 (743) 555-3824] now
mobile [phone 0171-5550142] please
her number is [phone 415.555.2671] if needed
dial [phone 1-800-555-0188] free
telefon [phone 089 5550123] berlin
tel [phone +44 20 7946 0991] london
the server at [ip 192.168.10.4] is down
host [ip 10.0.0.255] answers ping
from [ip 172.16.254.1] port 8080
ssh to [ip 203.0.113.77:22] first
address [ip 2001:db8:85a3::8a2e:370:7334] was blocked
gateway [ip fe80::1ff:fe23:4567:890a] replied
card [card 4111 1111 1111 1111] expires 12/29
pay with [card 5500-0000-0000-0004] today
visa [card 4785380592391139] charged
charge card number [card 4012.8888.8888.1881] again
amex [card 3782 822463 10005] approved
token = "[secret 24be64439e3e49cf46b2d7c90f3602a3d0b907ff]" was leaked
api_key: [secret 9f86d081884c7d659a2feaa0c55ad015] keep it safe
secret = '[secret 1eb9c654e721b4f812088970e66a6345cee33dd6]' here
password=[secret hunter2X9q] do not share
export TOKEN=[secret ghx81K2mNq0PzR5tUv7wYb3] in shell
key = "[secret f0ddae3b09ae356cbefecdd3232fa5489bb400d6]" then
aws key [secret AKQ7EXAMPLE4KEY9ZZ2B] rotates
bearer [secret eyJ0eXAiOiJKV1QiLCJh9] header
token = "[secret e03422dad6b454724135a384f69ba12c7de6c8f4]"
password=[secret openthisdoornow] was set
password: [secret correctbatteryhorse] works
password = "[secret swordfishandchips]" in the file
token=[secret abcdefghijklmnop] leaked
token = "[secret qwertzuiopasdfgh]" was found
api_key = "[secret zyxwvutsrqponmlk]" inside
secret: [secret mysecretvaluehere] end
write to [email info [at] company dot org] now
contact [email john dot smith (at) mail dot com] please
mail [email support (at) shop dot example dot net] today
the password was lost again
a password is needed for this
the secret garden is a book
a token of love and the key point
she has the key to the house
forgot your password? click here
look at the dot on the map
dot com companies fell
let x = y and z = w
a = b + c in the formula
the year 2019 was a good one
in 1984 and 2001 they met
page 12 of 300 shows it
version 2.4.1 fixes bug 1234
build 10.2.33 was released on 2023-04-17
it costs $45.00 or 39,99 euro
sold 1,200 units in 3 days
the meeting is at 10:30 on 12/05/2021
chapter 3 verse 16
a ratio of 3.14159 to 1
about 50% of 7000 people
model x200 and part b12 arrived
route 66 is 3945 km long
order 1234567 contains 8 items
figure 4 and table 2 list 15 rows
room 101 on floor 7
born 17.03.1975 in town
apollo 11 landed in july 1969
isbn 978-3-16-148410-0 is a book
h2o and co2 are molecules
mp3 and utf8 files
the 1st and 2nd of 10
@ home and @ work
follow @someone on the site
score 21-14 after 90 minutes
temperature fell to -12.5 degrees
zip 90210 and 10115
lines 100-120 and 200-240 changed
id 77 has value 0.25
copyright 2004-2010 by the authors
see section 4.2.1.3 of the manual
see rule 3.1.4 and 5.2
http://example.com/page/825?x=2 is a link
"""
PIECE = re.compile(r"\[(email|ip|card|phone|secret) ((?:[^\[\]]|\[at\])+)\]")
EDGE = "\"'`.,;:!?()[]{}<>#*$%&=|"
WORD = re.compile(r"\S+")


def shape(token: str) -> str:
    out, last = [], ""
    for c in token[:24]:
        s = "d" if "0" <= c <= "9" else "A" if c.isupper() else "a" if c.islower() else c
        if s != last:
            out.append(s)
        last = s
    return "".join(out)


def token_features(token: str) -> list[str]:
    core = token.strip(EDGE)
    digits = sum("0" <= c <= "9" for c in core)
    low = core.lower()
    out = [f"shape={shape(core)}", f"digits={min(digits, 20)}", f"len={min(len(core), 40) // 4}", f"word={low if digits == 0 and len(low) < 12 else '#'}"]
    if "@" in token:
        out.append("at")
    if digits and len(core) >= 16 and re.fullmatch(r"[0-9a-f]+|[0-9A-F]+", core) and digits < len(core):
        out.append("hex")
    if len(core) >= 12 and digits and any(c.isalpha() for c in core) and core.isalnum():
        out.append("mixed")
    if "=" in token or ":" in token:
        out.append("assign")
    if digits and digits == len(core):
        out.append("all_digits")
    if core.count(":") >= 3:
        out.append("colons")
    return out


def features(tokens: list[str]) -> list[list[str]]:
    own = [token_features(t) for t in tokens]
    out = []
    for i, f in enumerate(own):
        f = list(f)
        for k in (-2, -1, 1, 2):
            if 0 <= i + k < len(tokens):
                f += [f"{k}:{x}" for x in own[i + k][:2] + own[i + k][3:]]
            else:
                f.append(f"{k}:edge")
        out.append(f)
    return out


def labelled_rows() -> list[tuple[list[str], list[int]]]:
    """Tokens and labels of the table: 0 outside, 1 + 2k begins kind k, 2 + 2k continues it."""
    rows = []
    for line in LABELLED.strip().split("\n"):
        text, spans = "", []
        at = 0
        for m in PIECE.finditer(line):
            text += line[at : m.start()]
            spans.append((len(text), len(text) + len(m[2]), KINDS.index(m[1])))
            text += m[2]
            at = m.end()
        text += line[at:]
        tokens, labels = [], []
        for m in WORD.finditer(text):
            label = 0
            for a, b, k in spans:
                if m.start() < b and m.end() > a:
                    label = 1 + 2 * k + (m.start() > a)
            tokens.append(m[0])
            labels.append(label)
        rows.append((tokens, labels))
    return rows


class Field:
    """Weights of a linear-chain conditional random field."""

    labels = 1 + 2 * len(KINDS)

    def __init__(self, names: dict[str, int], emit: np.ndarray, move: np.ndarray):
        self.names, self.emit, self.move = names, emit, move

    def scores(self, segments: list[list[str]]) -> tuple[np.ndarray, np.ndarray]:
        """Padded emission scores (segment, place, label) and the segments' lengths."""
        lens = np.array([len(s) for s in segments])
        out = np.zeros((len(segments), int(lens.max()), self.labels))
        for i, s in enumerate(segments):
            for j, fs in enumerate(features(s)):
                at = [self.names[f] for f in fs if f in self.names]
                if at:
                    out[i, j] = self.emit[at].sum(axis=0)
        return out, lens

    def decode(self, segments: list[list[str]]) -> list[list[int]]:
        """Most likely labels of each segment, by Viterbi over the whole batch at once."""
        if not segments:
            return []
        scores, lens = self.scores(segments)
        n, t, k = scores.shape
        best = scores[:, 0] + self.move[k]
        back = np.zeros((n, t, k), np.int8)
        for j in range(1, t):
            step = best[:, :, None] + self.move[None, :k]
            back[:, j] = step.argmax(axis=1)
            new = step.max(axis=1) + scores[:, j]
            best = np.where((j < lens)[:, None], new, best)
        out = []
        for i in range(n):
            y = int(best[i].argmax())
            path = [y]
            for j in range(lens[i] - 1, 0, -1):
                y = int(back[i, j, y])
                path.append(y)
            out.append(path[::-1])
        return out


def allowed() -> np.ndarray:
    """Which label may follow which; the last row is the start."""
    k = Field.labels
    ok = np.ones((k + 1, k), bool)
    for y in range(2, k, 2):  # a continuation follows its own kind only
        ok[:, y] = False
        ok[[y - 1, y], y] = True
    return ok


def train(rows: list[tuple[list[str], list[int]]], steps: int = 160, rate: float = 0.3, penalty: float = 0.02) -> Field:
    """Maximise the penalised likelihood of the labelled rows by adaptive gradient ascent."""
    feats = [features(t) for t, _ in rows]
    names: dict[str, int] = {}
    for row in feats:
        for fs in row:
            for f in fs:
                names.setdefault(f, len(names))
    k = Field.labels
    lens = np.array([len(r) for r in feats])
    n, t = len(rows), int(lens.max())
    pos = [(i, j, names[f]) for i, row in enumerate(feats) for j, fs in enumerate(row) for f in fs]
    where = np.array([i * t + j for i, j, _ in pos])
    what = np.array([f for _, _, f in pos])
    gold = np.zeros((n * t, k))
    gold_move = np.zeros((k + 1, k))
    for i, (_, labels) in enumerate(rows):
        for j, y in enumerate(labels):
            gold[i * t + j, y] = 1
            gold_move[labels[j - 1] if j else k, y] += 1
    live = (np.arange(t)[None] < lens[:, None])[:, :, None]
    emit, move = np.zeros((len(names), k)), np.zeros((k + 1, k))
    bar = np.where(allowed(), 0.0, -1e4)
    seen_e, seen_m = np.full_like(emit, 1e-8), np.full_like(move, 1e-8)

    def log_sum(x, axis):
        m = x.max(axis=axis, keepdims=True)
        return np.squeeze(m, axis) + np.log(np.exp(x - m).sum(axis=axis))

    for _ in range(steps):
        s = np.zeros((n * t, k))
        np.add.at(s, where, emit[what])
        s = s.reshape(n, t, k)
        m = move + bar
        fwd, bwd = np.zeros((n, t, k)), np.zeros((n, t, k))
        fwd[:, 0] = s[:, 0] + m[k]
        for j in range(1, t):
            fwd[:, j] = np.where(live[:, j], log_sum(fwd[:, j - 1][:, :, None] + m[None, :k], 1) + s[:, j], fwd[:, j - 1])
        total = log_sum(fwd[:, -1], 1)
        for j in range(t - 2, -1, -1):
            bwd[:, j] = np.where(live[:, j + 1], log_sum(m[None, :k] + (s[:, j + 1] + bwd[:, j + 1])[:, None, :], 2), 0)
        p = np.where(live, np.exp(fwd + bwd - total[:, None, None]), 0)
        grad_m = gold_move.copy()
        grad_m[k] -= p[:, 0].sum(axis=0)
        for j in range(1, t):
            pair = np.exp(fwd[:, j - 1][:, :, None] + m[None, :k] + (s[:, j] + bwd[:, j])[:, None, :] - total[:, None, None])
            grad_m[:k] -= np.where(live[:, j][:, :, None], pair, 0).sum(axis=0)
        diff = gold - p.reshape(n * t, k)
        grad_e = np.zeros_like(emit)
        np.add.at(grad_e, what, diff[where])
        grad_e -= penalty * emit
        grad_m -= penalty * move
        seen_e += grad_e**2
        seen_m += grad_m**2
        emit += rate * grad_e / np.sqrt(seen_e)
        move += rate * grad_m / np.sqrt(seen_m)
    return Field(names, emit, move + bar)


@lru_cache(maxsize=1)
def default_field() -> Field:
    return train(labelled_rows())


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """Spans of the fixed patterns, by kind and then by start."""
    out = []
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in LOCAL:
            start -= 1
        if start < at and (m := DOMAIN.match(text, at + 1)):
            out.append(("email", start, m.end()))
            done = m.end()
        at = text.find("@", at + 1)
    if not DIGIT.search(text):
        return out
    for m in IP.finditer(text):
        if all(len(x.lstrip("0")) <= 3 and int(x.lstrip("0") or 0) <= 255 for x in m[0].split(".")):
            out.append(("ip", m.start(), m.end()))
    for m in CARD.finditer(text):
        d = m[0].replace(" ", "").replace("-", "")
        if 13 <= len(d) <= 19 and luhn(d):
            out.append(("card", m.start(), m.end()))
    for m in PHONE.finditer(text):
        if 9 <= sum("0" <= c <= "9" for c in m[0]) <= 15:
            out.append(("phone", m.start(), m.end()))
    return out


def segments_of(text: str, reach: int = 3) -> list[list[tuple[int, int]]]:
    """Runs of tokens (start, end) within ``reach`` of a token with a digit, at-sign or other cue, by line."""
    out, at = [], 0
    while m := CUE.search(text, at):
        lo = text.rfind("\n", 0, m.start()) + 1
        hi = text.find("\n", m.start())
        hi = len(text) if hi < 0 else hi
        hi = max(hi, m.end())
        tokens = [(lo + w.start(), lo + w.end()) for w in WORD.finditer(text[lo:hi])]
        cues = [(c.start(), c.end()) for c in CUE.finditer(text, lo, hi)]
        marked, k = [], 0
        for i, (a, b) in enumerate(tokens):
            while k < len(cues) and cues[k][1] <= a:
                k += 1
            if k < len(cues) and cues[k][0] < b:
                marked.append(i)
        run: list[int] = []
        for i in marked:
            if run and i - run[-1] > 2 * reach:
                out.append(tokens[max(0, run[0] - reach) : run[-1] + reach + 1])
                run = []
            run.append(i)
            if len(run) >= 200:  # keeps the batch's padding small
                out.append(tokens[max(0, run[0] - reach) : run[-1] + reach + 1])
                run = []
        if run:
            out.append(tokens[max(0, run[0] - reach) : run[-1] + reach + 1])
        at = hi
    return out


def plausible(kind: str, text: str) -> bool:
    """Cards keep their check digit and phones their length in any notation."""
    digits = "".join(c for c in text if "0" <= c <= "9")
    if kind == "card":
        return 13 <= len(digits) <= 19 and luhn(digits)
    return kind != "phone" or 7 <= len(digits) <= 15


class Taken:
    """Stretches of a text that spans cover: kept apart and in order, so a look-up is a bisection."""

    def __init__(self, spans: list[tuple[str, int, int]]):
        self.starts: list[int] = []
        self.ends: list[int] = []
        for a, b in sorted((a, b) for _, a, b in spans):
            if self.ends and a < self.ends[-1]:
                self.ends[-1] = max(self.ends[-1], b)
            else:
                self.starts.append(a)
                self.ends.append(b)

    def add(self, a: int, b: int) -> bool:
        """Takes a stretch that touches no other; says whether it could."""
        at = bisect_left(self.starts, b)
        if at and self.ends[at - 1] > a:
            return False
        self.starts.insert(at, a)
        self.ends.insert(at, b)
        return True


def field_spans(texts: list[str], base: list[list[tuple[str, int, int]]], field: Field) -> list[list[tuple[str, int, int]]]:
    """Spans that the random field adds to those of the patterns."""
    out: list[list[tuple[str, int, int]]] = [[] for _ in texts]
    taken = [Taken(own) for own in base]
    jobs = [(i, seg) for i, text in enumerate(texts) if text for seg in segments_of(text)]
    for lo in range(0, len(jobs), 256):
        part = jobs[lo : lo + 256]
        paths = field.decode([[texts[i][a:b] for a, b in seg] for i, seg in part])
        for (i, seg), path in zip(part, paths, strict=True):
            at = 0
            while at < len(path):
                if path[at] == 0:
                    at += 1
                    continue
                kind, end = (path[at] - 1) // 2, at + 1
                while end < len(path) and path[end] == 2 + 2 * kind:
                    end += 1
                a, b = seg[at][0], seg[end - 1][1]
                at = end
                if kind == 4 and (m := re.search(r"[=:]\s*", texts[i][a:b])):
                    a += m.end()
                while a < b and texts[i][a] in EDGE and not (kind == 3 and texts[i][a] == "("):
                    a += 1
                while b > a and texts[i][b - 1] in EDGE:
                    b -= 1
                if a < b and (kind in (0, 4) or MARK.search(texts[i], a, b)) and plausible(KINDS[kind], texts[i][a:b]) and taken[i].add(a, b):
                    out[i].append((KINDS[kind], a, b))
    return out


def listed(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(spans, key=lambda s: (KINDS.index(s[0]), s[1])))


def find_all(texts: list[str | None], field: Field) -> tuple[list, list]:
    texts = [t or "" for t in texts]
    base = [base_spans(t) if "@" in t or DIGIT.search(t) else [] for t in texts]
    return base, field_spans(texts, base, field)


FOUND = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string"


def found_batches(batches: Iterator[pa.RecordBatch], field: Field) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        base, more = find_all(batch.column("text").to_pylist(), field)
        cols = [pa.array([sum(s[0] == k for s in b) for b in base], pa.int64()) for k in BASE]
        digest = pa.array([hashlib.sha256(listed(b).encode()).hexdigest() for b in base], pa.string())
        spans = pa.array([listed(b + m) for b, m in zip(base, more, strict=True)], pa.string())
        names = ["doc_id", *(f"n_{k}" for k in BASE), "base_sha256", "spans"]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *cols, digest, spans], names)


def personal_data(docs: DataFrame, field: Field | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Counts of the patterns, their digest, and all spans of every document."""
    field = field or default_field()
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(lambda it: found_batches(it, field), FOUND)


def masked(text: str, spans: list[tuple[str, int, int]]) -> str:
    """The text with each span replaced by its kind; overlapping spans are replaced together."""
    out, at = [], 0
    for k, a, b in sorted(spans, key=lambda s: (s[1], -s[2])):
        if a >= at:
            out.append(text[at:a] + f"[{k.upper()}]")
        at = max(at, b)
    return "".join(out) + text[at:]


def redact(docs: DataFrame, field: Field | None = None, text_col: str = "text", chars_col: str | None = "n_chars") -> DataFrame:
    """``docs`` with personal data masked in the text, and its length brought up to date."""
    field = field or default_field()

    @F.pandas_udf("string")
    def clean(texts):
        own = [None if t is None or t != t else t for t in texts]
        base, more = find_all(own, field)
        out = [t if t is None or not b + m else masked(t, b + m) for t, b, m in zip(own, base, more, strict=True)]
        return texts.__class__(out, dtype=object)

    columns = [clean(F.col(c)).alias(c) if c == text_col else F.col(c) for c in docs.columns]
    out = docs.select(*columns)
    if chars_col and chars_col in docs.columns:
        new = F.when(F.col(text_col).isNotNull(), F.char_length(text_col)).otherwise(F.col(chars_col))
        out = out.withColumn(chars_col, new.cast(docs.schema[chars_col].dataType))
    return out


def query(spark, sf_dir: str) -> DataFrame:
    return personal_data(spark.read.parquet(f"{sf_dir}/documents.parquet"))
