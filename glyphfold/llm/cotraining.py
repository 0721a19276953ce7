"""Quality classifier by co-training of a text view and a metadata view.

Two logistic models judge each document for quality and for toxicity. The text view sees
the text alone: its words, the marks around them and how it is laid out. The metadata
view sees the other columns alone: language, source and stated length. Both start from
the labelled rows. In each round both score all unlabelled documents; of those a model is
sure of, some (drawn by a hash of the id, in the proportions of the labels) join the
training rows of the *other* model. Each view is then calibrated on labelled rows that
neither was trained on, and a logistic mixture of the calibrated views, fitted on the
same rows, scores every document.

The labelled rows to train on are a bounded sample, ``max_labelled`` documents chosen by
a hash of the id, and ``exchanged`` is how many documents a view passes on in a round.
Nothing else is bounded: rounds and scores cover all documents and whole texts.

Texts are read once: what the text view knows of them is written as a table of feature
numbers, from which rounds and scores are computed.

Defined cases: a null text has no words; null metadata is a value of its own;
unlabelled or one-sided label tables give the constant share of the label (quality 1
and toxicity 0 with no labels at all); of repeated labels the worst counts; repeated rows
are scored alike; a document of equal draw is passed on by its smaller id; a very long
text is held by one task at a time; an empty table gives no rows; other columns play no
part, whatever their names.
"""

from __future__ import annotations

import zlib
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from glyphfold.session import settle

TARGETS = ("quality", "toxic")
MARKS = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
#: Cells of the metadata view: hashed source names and languages, octaves of length.
SOURCES, LANGS, LENGTHS = 64, 8, 32
MAX_CACHE = 400_000


def features_of(token: str) -> tuple[str, ...]:
    """What the text view sees of a token: its word, and the marks and capitals around it."""
    core = token.strip(MARKS)
    end = token[len(token.rstrip(MARKS)) :]
    out = [core.lower()] if core else []
    if end:
        out.append("\0" + end[:4])
    if len(core) > 1 and core.isupper():
        out.append("\1")
    return tuple(out)


class _Seen(dict):
    def __missing__(self, token):
        self[token] = f = features_of(token)
        return f


def layout_of(text: str) -> list[str]:
    """How a text is laid out, as features: coarse shares of its characters, its lines and their length."""
    n, lines = len(text), text.count("\n") + 1
    upper = sum(map(text.count, "ABCDEFGHIJKLMNOPQRSTUVWXYZ"))
    digits = sum(map(text.count, "0123456789"))
    marks = sum(map(text.count, "#*$%&|<>!"))
    step = lambda x: int(4 * np.log2(1 + 1000 * x / (n + 1)))
    return [f"\2u{step(upper)}", f"\2d{step(digits)}", f"\2m{step(marks)}", f"\2s{step(text.count(' ') + lines)}", f"\2l{int(np.log2(lines))}", f"\2w{int(2 * np.log2(1 + n / lines))}"]


def text_features(text: str | None, seen: dict) -> set:
    """The text view of a document; ``seen`` maps a token to its features."""
    text = text or ""
    return {f for t in set(text.split()) for f in seen[t]}


def metadata(lang, source, n_chars) -> list[float]:
    """The metadata view of a document: a constant, its stated length, and cells of hashed source and language."""
    known = n_chars is not None and n_chars == n_chars
    out = [1.0, np.log1p(max(n_chars, 0)) / 8 if known else 0.0, float(not known)]
    cells = [0.0] * (LENGTHS + SOURCES + LANGS)
    if known:
        cells[min(LENGTHS - 1, int(np.log2(1 + max(n_chars, 0))))] = 1.0
    cells[LENGTHS + zlib.crc32((source if source is not None else "\0").encode()) % SOURCES] = 1.0
    cells[LENGTHS + SOURCES + zlib.crc32((lang if lang is not None else "\0").encode()) % LANGS] = 1.0
    return out + cells


N_META = 3 + LENGTHS + SOURCES + LANGS


def meta_rows(batch: pa.RecordBatch) -> np.ndarray:
    columns = (batch.column(c).to_pylist() for c in ("lang", "source", "n_chars"))
    known: dict[tuple, list[float]] = {}
    rows = [known[k] if k in known else known.setdefault(k, metadata(*k)) for k in zip(*columns, strict=True)]
    return np.array(rows, float).reshape(-1, N_META)


def view_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Both views of the labelled sample: distinct text features joined by newlines, and numbers."""
    seen = _Seen()
    for batch in batches:
        words = []
        for text in batch.column("text").to_pylist():
            words.append("\n".join(sorted(text_features(text, seen) | set(layout_of(text or "")))))
            if len(seen) > MAX_CACHE:
                seen.clear()
        keep = [batch.column(c) for c in ("doc_id", "quality", "toxic")]
        yield pa.RecordBatch.from_arrays([*keep, pa.array(words, pa.string()), pa.array(meta_rows(batch).tolist(), pa.list_(pa.float64()))], ["doc_id", "quality", "toxic", "words", "meta"])


def number_batches(batches: Iterator[pa.RecordBatch], vocab: dict[str, int]) -> Iterator[pa.RecordBatch]:
    """The text view of all documents as sorted numbers of known features; metadata as it is."""

    class Ids(dict):
        def __missing__(self, token):
            self[token] = f = tuple(vocab[x] for x in features_of(token) if x in vocab)
            return f

    seen = Ids()
    for batch in batches:
        rows = []
        for text in batch.column("text"):
            text = text.as_py()
            rows.append(np.array(sorted(text_features(text, seen) | {vocab[f] for f in layout_of(text or "") if f in vocab}), np.int32))
            if len(seen) > MAX_CACHE:
                seen.clear()
        names = ["doc_id", "lang", "source", "n_chars"]
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), pa.array(rows, pa.list_(pa.int32()))], [*names, "ids"])


def sigmoid(z):
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


class Rows:
    """Sparse 0/1 rows, or dense ones, with one interface for the optimiser."""

    def __init__(self, rows: list[np.ndarray] | np.ndarray, width: int):
        self.width = width
        self.dense = rows if isinstance(rows, np.ndarray) else None
        if self.dense is None:
            self.n = len(rows)
            self.row = np.repeat(np.arange(self.n), [len(r) for r in rows])
            self.col = np.concatenate(rows) if self.n else np.zeros(0, np.int64)

    def times(self, w: np.ndarray) -> np.ndarray:
        return self.dense @ w if self.dense is not None else np.bincount(self.row, w[self.col], self.n)

    def back(self, g: np.ndarray) -> np.ndarray:
        return self.dense.T @ g if self.dense is not None else np.bincount(self.col, g[self.row], self.width)


def logistic(x: Rows, y: np.ndarray, weight: np.ndarray, penalty: float, steps: int = 120, rate: float = 0.2) -> tuple[np.ndarray, float]:
    """Weights and offset of a penalised logistic model, by Adam on all rows."""
    w, b = np.zeros(x.width + 1), 0.0
    m, v = np.zeros_like(w), np.zeros_like(w)
    total = max(weight.sum(), 1e-9)
    for t in range(1, steps + 1):
        g = weight * (sigmoid(x.times(w[:-1]) + w[-1]) - y) / total
        grad = np.concatenate([x.back(g) + penalty * w[:-1], [g.sum()]])
        m = 0.9 * m + 0.1 * grad
        v = 0.999 * v + 0.001 * grad**2
        w -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8) * (1 - t / (steps + 1))
    return w[:-1], float(w[-1])


@dataclass
class Model:
    """Text weights by feature, metadata weights, and how calibrated views are mixed, per target."""

    vocab: dict[str, int]
    text: np.ndarray
    text_offset: np.ndarray
    meta: np.ndarray
    meta_offset: np.ndarray
    mix: np.ndarray  # (target, text / metadata / offset)
    constant: list

    def views(self, ids: list[np.ndarray], meta: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """What the text view and the metadata view say (row, target)."""
        size = np.array([len(r) for r in ids], np.int64)
        text = np.zeros((len(ids), 2))
        if size.sum():
            some = size > 0
            text[some] = np.add.reduceat(self.text[np.concatenate(ids)], (np.cumsum(size) - size)[some], axis=0)
        return text + self.text_offset, meta @ self.meta + self.meta_offset

    def logits(self, ids: list[np.ndarray], meta: np.ndarray) -> np.ndarray:
        """Calibrated mixture (row, target)."""
        a, b = self.views(ids, meta)
        return a * self.mix[:, 0] + b * self.mix[:, 1] + self.mix[:, 2]


def telling(words: list[list[str]], labels: np.ndarray, least_docs: int, least_z: float) -> list[str]:
    """Features whose share differs between the classes of either label by ``least_z`` standard errors."""
    count = Counter(f for row in words for f in row)
    common = sorted(f for f, c in count.items() if c >= least_docs)
    ids = {f: i for i, f in enumerate(common)}
    keep = np.zeros(len(common), bool)
    for t in range(labels.shape[1]):
        seen = []
        for y in (0, 1):
            own = np.flatnonzero(labels[:, t] == y)
            hits = Counter(ids[f] for i in own for f in words[i] if f in ids)
            seen.append((np.array([hits[i] for i in range(len(common))], float), len(own)))
        (a, n), (b, m) = seen
        if n and m:
            p = (a + b + 1) / (n + m + 2)
            keep |= np.abs(a / n - b / m) > least_z * np.sqrt(p * (1 - p) * (1 / n + 1 / m))
    return [f for f, k in zip(common, keep, strict=True) if k]


@dataclass
class Lesson:
    """Training rows of one view and target: features, labels and weights."""

    ids: list[np.ndarray]
    meta: np.ndarray
    y: np.ndarray
    weight: np.ndarray

    def plus(self, ids: list[np.ndarray], meta: np.ndarray, y: np.ndarray, weight: float) -> Lesson:
        return Lesson(self.ids + ids, np.concatenate([self.meta, meta]), np.concatenate([self.y, y]), np.concatenate([self.weight, np.full(len(y), weight)]))


class CoTraining:
    """The state of co-training on the driver: a bounded number of rows for each view and target."""

    PENALTY, PSEUDO = 0.0003, 0.1

    def __init__(self, words: list[list[str]], meta: np.ndarray, labels: np.ndarray, least_docs: int = 4, least_z: float = 3.0):
        """labels: (row, target); rows come in a random order, every fourth one is kept for calibration."""
        vocab = {f: i for i, f in enumerate(telling(words, labels, least_docs, least_z))}
        self.all_ids = [np.array(sorted(vocab[f] for f in row if f in vocab), np.int64) for row in words]
        self.all_meta, self.labels = meta, labels
        k = len(vocab)
        self.model = Model(vocab, np.zeros((k, 2)), np.zeros(2), np.zeros((meta.shape[1], 2)), np.zeros(2), np.zeros((2, 3)), [None, None])
        self.train: list[list[Lesson] | None] = [None, None]
        self.test: list[np.ndarray | None] = [None, None]
        self.share = [0.0, 0.0]
        for t in range(2):
            known = np.flatnonzero(labels[:, t] >= 0)
            y = labels[known, t].astype(float)
            if len(np.unique(y)) < 2 or len(known) < 20:
                self.model.constant[t] = float(y.mean()) if len(y) else float(t == 0)
                continue
            held = np.arange(len(known)) % 4 == 0
            self.test[t], own = known[held], known[~held]
            self.share[t] = float(labels[own, t].mean())
            self.train[t] = [self.rows(own, t)] * 2
        self.fit()

    def rows(self, at: np.ndarray, t: int) -> Lesson:
        return Lesson([self.all_ids[i] for i in at], self.all_meta[at], self.labels[at, t].astype(float), np.ones(len(at)))

    def fit(self) -> None:
        """Both views of every target, from their training rows."""
        m = self.model
        for t, views in enumerate(self.train):
            if views is not None:
                text, meta = views
                m.text[:, t], m.text_offset[t] = logistic(Rows(text.ids, len(m.vocab)), text.y, text.weight, self.PENALTY)
                m.meta[:, t], m.meta_offset[t] = logistic(Rows(meta.meta, meta.meta.shape[1]), meta.y, meta.weight, self.PENALTY)

    def teach(self, t: int, view: int, ids: list[np.ndarray], meta: np.ndarray, y: np.ndarray) -> None:
        """Rows that ``view`` is sure of teach the other view."""
        if self.train[t] is not None and len(y):
            self.train[t][1 - view] = self.train[t][1 - view].plus(ids, meta, y, self.PSEUDO)

    def quotas(self, exchanged: int) -> dict[tuple[int, int, int], int]:
        """Documents that each view of each target may pass on as positive (1) and as negative (0)."""
        out = {}
        for t in range(2):
            if self.train[t] is not None:
                for view in (0, 1):
                    out[t, view, 1] = max(1, round(exchanged * self.share[t]))
                    out[t, view, 0] = max(1, round(exchanged * (1 - self.share[t])))
        return out

    def finish(self) -> Model:
        """Calibrates each view on rows it has not seen, then mixes them."""
        for t, at in enumerate(self.test):
            if at is None:
                continue
            y, one = self.labels[at, t].astype(float), np.ones(len(at))
            a, b = self.model.views([self.all_ids[i] for i in at], self.all_meta[at])
            scaled = [logistic(Rows(z[:, t : t + 1], 1), y, one, 0.001) for z in (a, b)]
            calibrated = np.stack([w[0] * z[:, t] + c for (w, c), z in zip(scaled, (a, b), strict=True)], axis=1)
            mix, offset = logistic(Rows(calibrated, 2), y, one, 0.001)
            mix = np.maximum(mix, 0)
            (wa, ca), (wb, cb) = scaled
            self.model.mix[t] = [mix[0] * wa[0], mix[1] * wb[0], offset + mix[0] * ca + mix[1] * cb]
        return self.model


def arrays_of(column: pa.Array) -> list[np.ndarray]:
    """The rows of a list column of numbers, without a Python object for each number."""
    flat, cut = column.values.to_numpy(zero_copy_only=False), column.offsets.to_numpy()
    return [flat[a:b] for a, b in zip(cut[:-1], cut[1:], strict=True)]


def draws_of(ids: list) -> np.ndarray:
    return np.array([zlib.crc32(f"draw {i}".encode()) for i in ids], np.int64)


def sure_batches(batches: Iterator[pa.RecordBatch], model: Model, quotas: dict, taken: dict, bound: float) -> Iterator[pa.RecordBatch]:
    """Of the documents a view is sure of, those of the smallest draws, at most a quota for each kind and partition."""
    best: dict[tuple, list] = {k: [] for k in quotas}
    gone = {k: np.array(sorted(v), np.int64) for k, v in taken.items()}
    for batch in batches:
        names = batch.column("doc_id").to_numpy()
        ids, meta, draw = arrays_of(batch.column("ids")), meta_rows(batch), draws_of(names.tolist())
        views = [sigmoid(z) for z in model.views(ids, meta)]
        for key, room in quotas.items():
            t, view, label = key
            p = views[view][:, t] if label else 1 - views[view][:, t]
            most = best[key][-1][0] if len(best[key]) == room else np.inf
            at = np.flatnonzero((p > bound) & (draw <= most))
            if (t, view) in gone:
                at = at[~np.isin(names[at], gone[t, view])]
            if len(low := np.unique(draw[at])) > room:  # a larger draw than the quota's last can't be taken
                at = at[draw[at] <= low[room - 1]]
            own = {(r[0], r[1]): r for r in best[key]} | {(int(draw[i]), int(names[i])): (int(draw[i]), int(names[i]), ids[i].tolist(), meta[i].tolist()) for i in at.tolist()}
            best[key] = [own[k] for k in sorted(own)[:room]]
    rows = [(*key, *r) for key, own in best.items() for r in own]
    cols = list(zip(*rows, strict=True)) if rows else [()] * 7
    types = (pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.int32()), pa.list_(pa.float64()))
    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, types, strict=True)], ["target", "view", "label", "draw", "doc_id", "ids", "meta"])


SURE = "target int, view int, label int, draw long, doc_id long, ids array<int>, meta array<double>"


def exchange(state: CoTraining, pool: DataFrame, exchanged: int, taken: dict, bound: float = 0.9) -> int:
    """One round: all of ``pool`` is scored, and what either view is sure of teaches the other; how many rows that was."""
    quotas = state.quotas(exchanged)
    model = state.model
    sure = settle(pool.mapInArrow(lambda it: sure_batches(it, model, quotas, taken, bound), SURE), "sure")
    place = F.row_number().over(Window.partitionBy("target", "view", "label").orderBy("draw", "doc_id"))
    room = F.coalesce(*(F.when((F.col("target") == t) & (F.col("view") == v) & (F.col("label") == y), n) for (t, v, y), n in quotas.items()))
    rows = sure.dropDuplicates(["target", "view", "label", "doc_id"]).withColumn("place", place).where(F.col("place") <= room).orderBy("target", "view", "label", "place").toArrow()  # quotas bound it
    rows = rows.combine_chunks()
    for t, view in sorted({k[:2] for k in quotas}):
        own = rows.filter(pc.and_(pc.equal(rows["target"], t), pc.equal(rows["view"], view)))
        ids = [np.array(x, np.int64) for x in own["ids"].to_pylist()]
        meta = np.array(own["meta"].to_pylist(), float).reshape(-1, N_META)
        state.teach(t, view, ids, meta, own["label"].to_numpy().astype(float))
        taken[t, view] |= set(own["doc_id"].to_pylist())
    return rows.num_rows


def labelled_sample(docs: DataFrame, labels: DataFrame, max_labelled: int) -> DataFrame:
    """A bounded sample of the labelled documents, by a hash of the id; of repeated labels the worst."""
    worst = worst_labels(labels)
    known = worst.count()
    cut = int((1 << 30) * min(1.0, max_labelled / max(known, 1)))
    return docs.join(worst.where(F.pmod(F.xxhash64("doc_id", F.lit(17)), F.lit(1 << 30)) < cut), "doc_id")


def worst_labels(labels: DataFrame) -> DataFrame:
    return labels.groupBy("doc_id").agg(F.min("quality").alias("quality"), F.max("toxic").alias("toxic")).where("doc_id is not null")


def start(docs: DataFrame, labels: DataFrame, max_labelled: int = 4000) -> CoTraining:
    """Both views as the labelled sample teaches them."""
    rows = labelled_sample(docs, labels, max_labelled)
    rows = rows.select("doc_id", "text", "lang", "source", "n_chars", *(F.coalesce(F.col(t).cast("int"), F.lit(-1)).alias(t) for t in TARGETS))
    table = rows.mapInArrow(view_batches, "doc_id long, quality int, toxic int, words string, meta array<double>").toArrow()
    order = np.argsort([zlib.crc32(str(i).encode()) for i in table.column("doc_id").to_pylist()], kind="stable")
    words = table.column("words").to_pylist()
    meta = np.array(table.column("meta").to_pylist(), float).reshape(-1, N_META)
    y = np.stack([table.column(t).to_numpy() for t in TARGETS], axis=1)
    return CoTraining([words[i].split("\n") if words[i] else [] for i in order], meta[order], y[order])


def numbered_texts(docs: DataFrame, vocab: dict[str, int]) -> DataFrame:
    """``(doc_id, lang, source, n_chars, ids)`` of all documents, written once."""
    return settle(docs.mapInArrow(lambda it: number_batches(it, vocab), "doc_id long, lang string, source string, n_chars long, ids array<int>"), "text_views")


def fit(docs: DataFrame, labels: DataFrame, max_labelled: int = 4000, rounds: int = 3, exchanged: int = 450) -> tuple[Model, DataFrame]:
    """The model after all rounds, and the feature table of all documents."""
    labels = labels.select("doc_id", *TARGETS)
    state = start(docs, labels, max_labelled)
    table = numbered_texts(docs, state.model.vocab)
    pool = table.join(worst_labels(labels).select("doc_id"), "doc_id", "left_anti").where("doc_id is not null")
    taken: dict = defaultdict(set)
    for _ in range(rounds if state.quotas(exchanged) else 0):
        if not exchange(state, pool, exchanged, taken):
            break
        state.fit()
    return state.finish(), table


SCORED = "doc_id long, quality double, toxic double, kept boolean"


def score_batches(batches: Iterator[pa.RecordBatch], model: Model, least_quality: float, most_toxic: float) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        p = sigmoid(model.logits(arrays_of(batch.column("ids")), meta_rows(batch)))
        for t, c in enumerate(model.constant):
            if c is not None:
                p[:, t] = c
        kept = (p[:, 0] >= least_quality) & (p[:, 1] < most_toxic)
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(p[:, 0]), pa.array(p[:, 1]), pa.array(kept)], ["doc_id", "quality", "toxic", "kept"])


def quality_scores(docs: DataFrame, labels: DataFrame, model: Model | None = None, least_quality: float = 0.5, most_toxic: float = 0.5, **training) -> DataFrame:
    """``(doc_id, quality, toxic, kept)``: probabilities of every document, and whether it passes both bounds."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string"), F.col("lang").cast("string"), F.col("source").cast("string"), F.col("n_chars").cast("long"))
    model, table = (model, numbered_texts(rows, model.vocab)) if model else fit(rows, labels, **training)
    held = rows.sparkSession.sparkContext.broadcast(model)  # bounded by the sample
    return table.mapInArrow(lambda it: score_batches(it, held.value, least_quality, most_toxic), SCORED)


def query(spark, sf_dir: str) -> DataFrame:
    return quality_scores(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))
