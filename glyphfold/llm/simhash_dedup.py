"""SimHash near-duplicates linked through the words of a covering code.

Two 64-bit fingerprints at distance 3 or less agree, but for one bit at most, in
one of their 32-bit halves. Anchors of a half are the words of the extended
covering code "perfect 31-bit Hamming code, plus a free bit": its covering radius
is 1, so every half has a home anchor within 1, and a half that differs in one
bit lies within 1 + 1 of that anchor. Each distinct fingerprint is filed once
under its home anchor and once under every anchor within radius plus threshold;
homes are compared with visitors of the same anchor only. No linked pair is missed.

Copies of a fingerprint are folded first (smallest id stands for them). An anchor
with very many homes is split by four pieces of the other half, one of which two
linked fingerprints must share; what is still hot is split again by four pieces of
the bits left, four times at most, when 21 bits or more of the other half agree beside
the anchor. Within a part only the edges of a spanning forest leave the task.

Defined cases: null or empty text has no words and fingerprint zero, linked like
any other; fewer words than a shingle: the whole sequence is the one shingle;
repeated rows share a fingerprint; null ids get a component but are no one's smallest
id; a very long text is held by one task, its hashes 200,000 at a time with those of
its neighbours; an empty table gives no rows; other columns play no part, whatever
their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType, StructField, StructType

from glyphfold.operators.components import connected_components
from glyphfold.llm.suffix_dedup import mixed
from glyphfold.session import discard, settle, whole_row

LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
#: Homes of one anchor above which it is split.
HOT_ANCHOR = 256
#: Independent families of fingerprints that can share one search.
SPACES = 8
U1 = np.uint64(1)


def shingle_hashes(text: str | None, width: int = 3, seed: int = 42) -> list[int]:
    """XXH64 of the space-joined word shingles, repeats included."""
    words = (text or "").encode("utf-8", "replace").translate(LOWER).split()
    if not words:
        return []
    digest = xxhash.xxh64_intdigest
    if len(words) < width:
        return [digest(b" ".join(words), seed)]
    joined = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = [0, *(ends[: len(words) - width] + 1).tolist()]
    return [digest(joined[a:b], seed) for a, b in zip(starts, ends[width - 1 :].tolist(), strict=True)]


def fold_bits(hashes: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Majority bits of consecutive runs of hashes; a run of none gives zero."""
    out = np.zeros(len(counts), np.uint64)
    some = counts > 0
    if not some.any():
        return out
    size = counts[some]
    starts = np.concatenate([[0], np.cumsum(size)[:-1]])
    fp = np.zeros(len(size), np.uint64)
    for b in range(64):
        ones = np.add.reduceat(((hashes >> np.uint64(b)) & U1).astype(np.int64), starts)
        fp |= (2 * ones > size).astype(np.uint64) << np.uint64(b)
    out[some] = fp
    return out


def fingerprint_batches(batches: Iterator[pa.RecordBatch], width: int = 3, seed: int = 42) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        hashes, counts, fps = [], [], []
        room = 0

        def flush():
            nonlocal hashes, counts, room
            if counts:
                fps.append(fold_bits(np.array(hashes, np.uint64), np.array(counts, np.int64)))
            hashes, counts, room = [], [], 0

        for text in batch.column("text"):
            h = shingle_hashes(text.as_py(), width, seed)
            hashes.extend(h)
            counts.append(len(h))
            room += len(h)
            if room > 200_000:
                flush()
        flush()
        fp = np.concatenate(fps) if fps else np.zeros(0, np.uint64)
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(fp.view(np.int64))], ["doc_id", "fp"])


def syndromes(half: np.ndarray) -> np.ndarray:
    """Position (1..31) of the bit to flip for the nearest code word, 0 at a word."""
    s = np.zeros(half.shape, np.uint32)
    for p in range(1, 32):
        s ^= np.where((half >> np.uint32(p - 1)) & np.uint32(1), np.uint32(p), np.uint32(0))
    return s


def bit_of(p: np.ndarray) -> np.ndarray:
    """Mask of position p; position 0 has none."""
    return np.where(p > 0, np.uint32(1) << (np.maximum(p, 1) - 1).astype(np.uint32), np.uint32(0)).astype(np.uint32)


def anchors(half: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Home anchor of each 32-bit half; row numbers and anchors of all within 2."""
    s = syndromes(half)
    home = half ^ bit_of(s)
    n = np.arange(len(half))
    rows, near = [n, n], [home, home ^ np.uint32(1 << 31)]
    off = np.flatnonzero(s)
    for i in range(1, 32):
        j = s[off] ^ np.uint32(i)
        ok = (j > i) & (j != 0)
        rows.append(off[ok])
        near.append(half[off[ok]] ^ bit_of(np.full(ok.sum(), i, np.uint32)) ^ bit_of(j[ok]))
    return home, np.concatenate(rows), np.concatenate(near)


def filed(batches: Iterator[pd.DataFrame], visits: bool = True) -> Iterator[pd.DataFrame]:
    """Records of distinct fingerprints under the anchors of both halves; homes only without ``visits``."""
    for df in batches:
        fp = df["fp"].to_numpy(np.int64).view(np.uint64)
        ids, space = df["id"].to_numpy(np.int64), df["space"].to_numpy(np.int64)
        for side in (0, 1):
            half = (fp >> np.uint64(32 * side)).astype(np.uint32)
            home, rows, near = anchors(half)
            key = lambda a, sp: (a.astype(np.int64) * 2 + side) * SPACES + sp  # noqa: B023,E731
            yield pd.DataFrame({"anchor": key(home, space), "visitor": False, "fp": fp.view(np.int64), "id": ids})
            if not visits:
                continue
            yield pd.DataFrame({"anchor": key(near, space[rows]), "visitor": True, "fp": fp[rows].view(np.int64), "id": ids[rows]})


def bit_count(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x)


def forest(homes: tuple, visitors: tuple, radius: int, block: int = 512) -> list[tuple[int, int]]:
    """Edges of a spanning forest of the links between homes and visitors."""
    hf, hi = homes
    vf, vi = visitors
    parent: dict[int, int] = {}

    def find(a: int) -> int:
        while parent.get(a, a) != a:
            parent[a] = parent.get(parent[a], parent[a])
            a = parent[a]
        return a

    edges = []
    for at in range(0, len(hf), block):
        near = bit_count(hf[at : at + block, None] ^ vf[None, :]) <= radius
        for r, c in zip(*np.nonzero(near), strict=True):
            a, b = int(hi[at + r]), int(vi[c])
            if a != b and (ra := find(a)) != (rb := find(b)):
                parent[max(ra, rb)] = min(ra, rb)
                edges.append((a, b))
    return edges


def linked(batches: Iterator[pd.DataFrame], radius: int) -> Iterator[pd.DataFrame]:
    """Links within each run of one ``part``; rows come sorted by it."""

    def run(df: pd.DataFrame) -> list[tuple[int, int]]:
        part = df["part"].to_numpy()
        fp = df["fp"].to_numpy(np.int64).view(np.uint64)
        ids, visitor = df["id"].to_numpy(np.int64), df["visitor"].to_numpy(bool)
        cut = np.flatnonzero(part[1:] != part[:-1]) + 1
        starts, ends = np.r_[0, cut], np.r_[cut, len(part)]
        has_home = np.add.reduceat(~visitor, starts) > 0
        edges = []
        for a, b in zip(starts[has_home], ends[has_home], strict=True):
            if b - a > 2:  # a home's own visits are there too
                v = visitor[a:b]
                edges += forest((fp[a:b][~v], ids[a:b][~v]), (fp[a:b][v], ids[a:b][v]), radius)
        return edges

    rest: pd.DataFrame | None = None
    for df in batches:
        df = df if rest is None else pd.concat([rest, df], ignore_index=True)
        if not len(df):
            continue
        part = df["part"].to_numpy()
        tail = int(np.flatnonzero(part != part[-1])[-1]) + 1 if (part != part[-1]).any() else 0
        rest = df.iloc[tail:]
        if tail:
            yield pd.DataFrame(run(df.iloc[:tail]), columns=["src", "dst"], dtype="int64")
    if rest is not None and len(rest):
        yield pd.DataFrame(run(rest), columns=["src", "dst"], dtype="int64")


#: How the other half of a fingerprint is cut each time an anchor is still hot: into four pieces of what is left.
PIECES = ((8, 8, 8, 8), (6, 6, 6, 6), (5, 5, 4, 4), (4, 4, 3, 3))


def divided(records: DataFrame, hot: DataFrame, level: int, widths: tuple[int, ...]) -> DataFrame:
    """Records of hot parts filed by each piece of what is left of the other half; two that differ in 3 bits share one piece."""
    pieces, at = [], 0
    for i, width in enumerate(widths):
        value = F.shiftrightunsigned("rest", at).bitwiseAND(F.lit((1 << width) - 1))
        left = F.col("rest").bitwiseAND(F.lit((1 << at) - 1)).bitwiseOR(F.shiftleft(F.shiftrightunsigned("rest", at + width), at))
        pieces.append(F.struct(F.xxhash64("part", F.lit(4 * level + i), value).alias("part"), left.alias("rest")))
        at += width
    same = F.array(F.struct("part", "rest"))
    out = records.join(hot, "part", "left").withColumn("piece", F.explode(F.when(F.col("hot"), F.array(*pieces)).otherwise(same)))
    return out.select("piece.part", "piece.rest", "visitor", "fp", "id")


def links(prints: DataFrame, radius: int = 3) -> DataFrame:
    """``(src, dst)`` edges that connect all of ``prints(id, fp)`` within ``radius`` (3 at most).

    With a column ``space`` (below 8) only fingerprints of the same space are compared.
    """
    if radius > 3:
        raise ValueError("the anchors cover distances up to 3")
    spark = prints.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    if "space" not in prints.columns:
        prints = prints.withColumn("space", F.lit(0).cast("long"))
    prints = prints.select("id", "fp", "space")
    record = "anchor long, visitor boolean, fp long, id long"
    other = F.when(F.shiftright("anchor", 3) % 2 == 0, F.shiftrightunsigned("fp", 32)).otherwise(F.col("fp")).bitwiseAND(F.lit(0xFFFFFFFF))
    fields = [F.col("anchor").alias("part"), other.alias("rest"), "visitor", "fp", "id"]
    homes = prints.mapInPandas(lambda it: filed(it, False), record).select(*fields)
    records = prints.mapInPandas(filed, record).select(*fields)
    for level, widths in enumerate(PIECES):
        hot = settle(homes.groupBy("part").count().where(F.col("count") > HOT_ANCHOR).select("part", F.lit(True).alias("hot")), "hot_anchors")  # of known size
        if hot.isEmpty():
            break
        homes, records = divided(homes, hot, level, widths), divided(records, hot, level, widths)
    return (
        records.select("part", "visitor", "fp", "id")
        .repartition(n, "part")
        .sortWithinPartitions("part")
        .mapInPandas(lambda it: linked(it, radius), "src long, dst long")
    )


def fingerprints(docs: DataFrame, width: int = 3, seed: int = 42, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(
        lambda it: fingerprint_batches(it, width, seed), "doc_id long, fp long"
    )


def simhash_components(docs: DataFrame, width: int = 3, radius: int = 3, seed: int = 42, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, fp, component_id)``: smallest id reachable over links of fingerprints."""
    prints = settle(fingerprints(docs, width, seed, id_col, text_col), "prints")
    return prints.join(print_components(prints, radius, "doc_id"), "fp", "left").select("doc_id", "fp", "component_id")


def print_components(prints: DataFrame, radius: int = 3, id_col: str = "id") -> DataFrame:
    """``(fp, component_id)`` of all fingerprints ``fp`` with an id: smallest id reachable over links of fingerprints."""
    distinct = settle(prints.groupBy("fp").agg(F.min(id_col).alias("id")).where("id is not null"), "distinct_prints")
    roots = connected_components(links(distinct, radius))
    return distinct.join(roots, "id", "left").select("fp", F.coalesce("root", "id").alias("component_id"))


def band_batches(batches: Iterator[pa.RecordBatch], width: int, bands: int, per_band: int, text_col: str = "text") -> Iterator[pa.RecordBatch]:
    """``row`` as it comes, with a number of its own, a hash of all its words, one key per band, and its fingerprint.

    The fingerprint is that of ``fingerprints``. A key is made of minima of the shingles'
    hashes: two texts of similarity s agree in a band with chance s ** per_band; a text
    without words has no keys.
    """
    draw = np.random.default_rng(42)
    factors = draw.integers(1 << 62, 1 << 63, (bands, per_band), np.uint64) | U1
    row = TaskContext.get().partitionId() << 33
    for batch in batches:
        whole, hashes, counts, out = [], [], [], []
        print_hashes, print_counts, prints = [], [], []

        def flush():
            n = np.array(counts, np.int64)
            prints.append(fold_bits(np.array(print_hashes, np.uint64), np.array(print_counts, np.int64)))
            print_hashes.clear()
            print_counts.clear()
            keys = np.zeros((len(n), bands), np.uint64)
            if hashes:
                h, some = np.array(hashes, np.uint64), n > 0
                starts = np.concatenate([[0], np.cumsum(n[some])[:-1]])
                room = np.empty_like(h)
                for k in range(bands):
                    key = np.full(len(starts), k, np.uint64)
                    for f in factors[k]:
                        np.multiply(h, f, out=room)
                        key = mixed(key * np.uint64(0x9E3779B97F4A7C15) + np.minimum.reduceat(room, starts))
                    keys[some, k] = key
            out.extend(row if c else row[:0] for row, c in zip(keys.view(np.int64), counts, strict=True))
            hashes.clear()
            counts.clear()

        for text in batch.column("row").field(text_col):
            text = text.as_py()
            words = (text or "").encode("utf-8", "replace").translate(LOWER).split()
            whole.append(xxhash.xxh64_intdigest(b" ".join(words)) - (1 << 63))
            own = shingle_hashes(text, width)
            hashes.extend(own)
            counts.append(len(own))
            own = shingle_hashes(text)
            print_hashes.extend(own)
            print_counts.append(len(own))
            if len(hashes) > 200_000:
                flush()
        flush()
        more = [pa.array(np.arange(row, row + len(batch))), pa.array(whole, pa.int64()), pa.array(out, pa.list_(pa.int64())), pa.array(np.concatenate(prints).view(np.int64))]
        row += len(batch)
        yield pa.RecordBatch.from_arrays([batch.column("row"), *more], ["row", "id", "whole", "keys", "fp"])


def shingle_set_batches(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sets = [np.unique(np.array(shingle_hashes(t.as_py(), width), np.uint64)).view(np.int64) for t in batch.column("text")]
        yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(sets, pa.list_(pa.int64()))], ["id", "s"])


def banded(docs: DataFrame, width: int = 5, bands: int = 24, per_band: int = 4, text_col: str = "text") -> DataFrame:
    """``(row, id, whole, keys, fp)`` of all rows, written once: numbers, keys and fingerprints stay as they are."""
    rows = docs.select(whole_row(docs))
    schema = StructType([*rows.schema.fields, StructField("id", LongType()), StructField("whole", LongType()), StructField("keys", ArrayType(LongType())), StructField("fp", LongType())])
    return settle(rows.mapInArrow(lambda it: band_batches(it, width, bands, per_band, text_col), schema), "banded")


def bucket_links(labels: np.ndarray, sets: list[np.ndarray], similarity: float) -> list[tuple[int, int]]:
    """Links (label, label) that join all texts of one bucket with sets of the given similarity; as few as do that."""
    parent: dict[int, int] = {}

    def find(a: int) -> int:
        while parent.get(a, a) != a:
            parent[a] = parent.get(parent[a], parent[a])
            a = parent[a]
        return a

    edges = []
    apart = len(set(labels.tolist()))
    size = np.array([len(x) for x in sets], np.int64)
    if apart > 1:
        tokens, where = np.unique(np.concatenate(sets), return_inverse=True)
        owner = np.repeat(np.arange(len(sets)), size)[np.argsort(where, kind="stable")]
        holders = np.split(owner, np.cumsum(np.bincount(where, minlength=len(tokens)))[:-1])
        ends = np.cumsum(size)
    for i in range(len(sets)):
        if apart < 2:
            break
        own = where[ends[i] - size[i] : ends[i]]
        both = np.bincount(np.concatenate([holders[t] for t in own]), minlength=len(sets))
        near = both >= (size[i] + size - both) * similarity - 1e-9
        for j in np.flatnonzero(near[i + 1 :]) + i + 1:
            a, b = int(labels[i]), int(labels[j])
            if (ra := find(a)) != (rb := find(b)):
                parent[max(ra, rb)] = min(ra, rb)
                edges.append((a, b))
                apart -= 1
    return edges


def linked_buckets(batches: Iterator[pd.DataFrame], similarity: float) -> Iterator[pd.DataFrame]:
    """Links within each run of one ``part``; rows (part, label, s) come sorted by it."""
    at, labels, sets = None, [], []

    def done() -> pd.DataFrame:
        found = bucket_links(np.array(labels, np.int64), sets, similarity)
        return pd.DataFrame(found, columns=["src", "dst"], dtype="int64")

    for df in batches:
        for part, label, own in zip(df["part"].tolist(), df["label"].tolist(), df["s"], strict=True):
            if part != at and sets:
                yield done()
                labels, sets = [], []
            at = part
            labels.append(label)
            sets.append(np.asarray(own, np.int64))
    if sets:
        yield done()


#: Texts of one key that are compared in one task; more are dealt out as pairs of blocks.
BUCKET_TEXTS = 1000


def linked_texts(open_: DataFrame, sets: DataFrame, similarity: float, rounds: tuple[int, ...] = (1, 1, 3, 8)) -> DataFrame:
    """``(id, root)``: all texts that some chain of links of the given similarity joins, by texts that share a key.

    open_ has (id, band, key), sets (id, s). Band 0 is the component of the fingerprint, the
    others are minima. Bands are taken in a few rounds, the first ones alone: most copies
    meet there. Later rounds compare what is still apart only, and a bucket's sets are
    shuffled only if it holds texts of two groups. No pairs leave a task, just the links of
    a spanning forest.
    """
    n = int(open_.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    edges, first = None, 0
    label = open_.select("id").distinct().withColumn("label", F.col("id"))
    for some in (*rounds, None):
        own = open_.where(F.col("band") >= first) if some is None else open_.where((F.col("band") >= first) & (F.col("band") < first + some))
        first += some or 0
        rows = settle(own.join(label, "id").select("key", "id", "label"), "bucket_rows")
        mixed_keys = rows.groupBy("key").agg(F.count("*").alias("texts"), F.min("label").alias("low"), F.max("label").alias("high")).where("low < high").select("key", "texts")
        mixed_keys = settle(mixed_keys, "mixed_buckets")
        blocks = F.ceil(F.col("texts") / BUCKET_TEXTS).cast("int")
        mine = F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int")
        # a text of block i meets the blocks before it, itself and those after it
        meets = F.when(F.col("blocks") > 1, F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda j: F.xxhash64("key", F.least(j, F.col("mine")), F.greatest(j, F.col("mine"))))).otherwise(F.array(F.xxhash64("key", F.lit(0), F.lit(0))))
        parts = rows.join(mixed_keys, "key").withColumn("blocks", blocks).withColumn("mine", mine).select("id", "label", F.explode(meets).alias("part"))
        found = parts.join(sets, "id").select("part", "label", "s").repartition(n, "part").sortWithinPartitions("part")
        found = settle(found.mapInPandas(lambda it: linked_buckets(it, similarity), "src long, dst long"), "text_links")
        discard(rows)
        discard(mixed_keys)
        edges = found if edges is None else edges.unionByName(found)
        if not found.isEmpty():
            roots = connected_components(edges)
            label = settle(label.select("id").join(roots, "id", "left").select("id", F.coalesce("root", "id").alias("label")), "text_labels")
    return label.where("id <> label").select("id", F.col("label").alias("root"))


def grouped_rows(band: DataFrame, similarity: float = 0.8, width: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, doc, kept, kept_doc)``: numbers and document ids of rows to drop, and of the one of their group that stays.

    Texts are linked if their sets of ``width``-word shingles have the similarity; links
    make groups, as with fingerprints. The first row of a group stays, in the order of
    document ids (null last), then of row numbers. Equal texts (up to case and white
    space) are folded before. Fingerprints are linked as in ``simhash_components``, and the
    texts of a component are compared by their exact sets. What is still apart after that is
    compared if it shares a key of minima: at ``similarity`` most fingerprints differ in more
    than 3 bits, and their groups would be lost.
    """
    doc = F.coalesce(F.col("row")[id_col].cast("long"), F.lit((1 << 63) - 1))
    prints = band.select("id", doc.alias("doc"), "whole", "keys", "fp")
    least = settle(prints.groupBy("whole").agg(F.min(F.struct("doc", "id")).alias("first")).select("whole", F.col("first.id").alias("text_id"), F.col("first.doc").alias("text_doc")), "texts")
    firsts = prints.join(least.select(F.col("text_id").alias("id")), "id", "left_semi")
    worded = firsts.where(F.size("keys") > 0).select("id", "fp", "keys")
    component = settle(worded.select("id", "fp").join(print_components(worded), "fp").select("id", F.lit(0).alias("band"), F.xxhash64("component_id", F.lit("print")).alias("key")), "print_components")
    long = component.unionByName(worded.select("id", F.posexplode("keys").alias("band", "key")).withColumn("band", F.col("band") + 1))
    many = settle(long.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key"), "shared_keys")  # of known size
    open_ = settle(long.join(many, "key").select("id", "band", "key"), "near_open")
    texts = band.select("id", F.col("row")[text_col].alias("text")).join(open_.select("id").distinct(), "id", "left_semi")
    sets = settle(texts.mapInArrow(lambda it: shingle_set_batches(it, width), "id long, s array<long>"), "shingle_sets")
    roots = linked_texts(open_, sets, similarity)
    group = least.join(roots.withColumnRenamed("id", "text_id"), "text_id", "left").select("whole", "text_id", "text_doc", F.coalesce("root", "text_id").alias("root"))
    # only groups of several texts need another look for their first one
    several = group.join(roots.select("root").distinct(), "root", "left_semi").groupBy("root").agg(F.min(F.struct(F.col("text_doc").alias("doc"), F.col("text_id").alias("id"))).alias("first"))
    several = settle(several.select("root", F.col("first.id").alias("group_id"), F.col("first.doc").alias("group_doc")), "groups")
    stays = group.join(several, "root", "left").select("whole", F.coalesce("group_id", "text_id").alias("kept"), F.coalesce("group_doc", "text_doc").alias("kept_doc"))
    return prints.join(stays, "whole").where("id <> kept").select("id", "doc", "kept", "kept_doc")


def near_duplicates(
    docs: DataFrame, similarity: float = 0.8, width: int = 5, bands: int = 24, per_band: int = 4, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """``(id, kept)``: documents to drop, each with the one of its group that stays."""
    gone = grouped_rows(banded(docs, width, bands, per_band, text_col), similarity, width, id_col, text_col)
    real = lambda c: F.nullif(F.col(c), F.lit((1 << 63) - 1))
    return gone.select(real("doc").alias("id"), real("kept_doc").alias("kept"))


def near_dedup(
    docs: DataFrame, similarity: float = 0.8, width: int = 5, bands: int = 24, per_band: int = 4, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """The first row of every group of near copies, columns unchanged.

    Rows are judged one by one, so two of equal id but different texts both stay, and of
    rows repeated as a whole one does. Null ids come last. Null and empty texts and those
    of white space are equal to each other; texts shorter than a shingle are one shingle.
    A text is held as a whole by one task at a time. Empty tables stay empty. A pair at
    ``similarity`` shares none of the keys with chance (1 - similarity ** per_band) ** bands,
    3e-6 by default.
    """
    band = banded(docs, width, bands, per_band, text_col)
    gone = grouped_rows(band, similarity, width, id_col, text_col).select("id")
    return band.join(gone, "id", "left_anti").select("row.*")


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = simhash_components(docs)
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
