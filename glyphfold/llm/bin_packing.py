"""Best-fit packing by minimum bin slack.

Texts are tokenised once; only piece lengths matter for packing, so the corpus
reaches the planner as one count per length (at most ``capacity`` of them). The
planner fills bin after bin: it fixes the longest piece left and finds, by a
subset-sum dynamic programme over bitsets of reachable fills, the fullest
combination of the lengths that are left. A combination is used as often as the
counts allow before the next is sought, so planning does not grow with the corpus.
Pieces are then ranked within their length (a range sort) and look up their place.

Defined cases: a null or empty text is the end token alone; a null id is packed like
any other; repeated rows are packed each; pieces of equal length take places in the order
of document ids and pieces; a very long text is encoded as a whole by one task; an empty
table gives no rows; other columns are not read, whatever their names.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from glyphfold.llm.hilbert_shards import ranked
from glyphfold.session import settle

#: Beyond these letters, or with a special token's name in the text, only the reference encoder is used.
PLAIN = re.compile("[^\x00-ɏ]")
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
PLACED = PIECES + ", sequence_id long, offset long"


class Encoder:
    """Token ids of a ``tokenizers`` file; ordinary Latin text goes by its rank table, which is faster."""

    def __init__(self, path: str, ranks_path: str | None):
        from tokenizers import Tokenizer

        self.reference = Tokenizer.from_file(path)
        self.special = [t.content for t in self.reference.get_added_tokens_decoder().values()]
        self.fast = None
        if ranks_path:
            import base64

            import public_tokenizers
            import tiktoken

            with open(ranks_path, "rb") as f:
                ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
            self.fast = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    def __call__(self, text: str) -> list[int]:
        if self.fast is not None and not PLAIN.search(text) and not any(s in text for s in self.special):
            return self.fast.encode_ordinary(text)
        return self.reference.encode(text, add_special_tokens=False).ids


@lru_cache(maxsize=2)
def encoder(path: str, ranks_path: str | None) -> Encoder:
    return Encoder(path, ranks_path)


def cut(n: int, capacity: int) -> list[tuple[int, int]]:
    """Start and length of the pieces of n tokens; all but the first are full."""
    first = n % capacity or capacity
    return [(0, first), *((at, capacity) for at in range(first, n, capacity))]


def piece_batches(batches: Iterator[pa.RecordBatch], path: str, ranks_path: str | None, end_id: int, capacity: int) -> Iterator[pa.RecordBatch]:
    encode = encoder(path, ranks_path)
    for batch in batches:
        cols: tuple[list, ...] = ([], [], [], [], [])
        for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text"), strict=True):
            ids = encode(text.as_py() or "")
            ids.append(end_id)
            raw = np.array(ids, "<u4").tobytes()
            for k, (start, length) in enumerate(cut(len(ids), capacity)):
                for c, v in zip(cols, (doc, k, start, length, zlib.crc32(raw[4 * start : 4 * (start + length)])), strict=True):
                    c.append(v)
        types = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
        names = ["doc_id", "piece", "start", "length", "ids_crc32"]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names)


def fullest(counts: dict[int, int], room: int) -> dict[int, int]:
    """The combination of available lengths with the largest sum up to ``room``; longer pieces first."""
    if counts.get(room):
        return {room: 1}
    lengths = sorted(k for k, c in counts.items() if c and k <= room)
    mask = (1 << (room + 1)) - 1
    reach, steps = 1, []
    for k in lengths:
        steps.append(reach)
        left, unit = min(counts[k], room // k), 1
        while left:
            take = min(unit, left)
            reach |= (reach << (k * take)) & mask
            left -= take
            unit *= 2
        if reach >> room & 1:
            lengths = lengths[: len(steps)]
            break
    target = reach.bit_length() - 1
    used: dict[int, int] = {}
    for k, before in zip(reversed(lengths), reversed(steps), strict=True):
        for u in range(min(counts[k], target // k), -1, -1):
            if before >> (target - u * k) & 1:
                if u:
                    used[k] = u
                    target -= u * k
                break
    return used


def plan(counts: dict[int, int], capacity: int) -> tuple[np.ndarray, int]:
    """Rows (length, first rank, pieces per bin, first bin, offset), sorted, and the number of bins."""
    left = {k: c for k, c in counts.items() if c}
    given = dict.fromkeys(left, 0)
    rows, bins = [], 0
    while left:
        top = max(left)
        rest = dict(left)
        rest[top] -= 1
        use = fullest(rest, capacity - top) if capacity > top else {}
        use[top] = use.get(top, 0) + 1
        times = min(left[k] // u for k, u in use.items())
        offset = 0
        for k, u in sorted(use.items(), reverse=True):
            rows.append((k, given[k], u, bins, offset))
            offset += k * u
            given[k] += u * times
            left[k] -= u * times
            if not left[k]:
                del left[k]
        bins += times
    return np.array(sorted(rows), np.int64).reshape(-1, 5), bins


def place_batches(batches: Iterator[pa.RecordBatch], table: np.ndarray, before: dict[int, int]) -> Iterator[pa.RecordBatch]:
    # first rank in the order of all pieces: rows of the plan are then sorted by it
    first = np.array([before[int(k)] for k in table[:, 0]], np.int64) + table[:, 1]
    for batch in batches:
        rank = batch.column("rank").to_numpy(zero_copy_only=False)
        row = table[np.searchsorted(first, rank, side="right") - 1]
        at = rank - first[np.searchsorted(first, rank, side="right") - 1]
        seq = row[:, 3] + at // row[:, 2]
        offset = row[:, 4] + (at % row[:, 2]) * row[:, 0]
        keep = [batch.column(i) for i in range(5)]
        yield pa.RecordBatch.from_arrays([*keep, pa.array(seq), pa.array(offset)], [*batch.schema.names[:5], "sequence_id", "offset"])


def tokenised(docs: DataFrame, path: str, ranks_path: str | None, end_id: int, capacity: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a piece with its place in the document and the checksum of its ids."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(
        lambda it: piece_batches(it, path, ranks_path, end_id, capacity), PIECES
    )


def pack(docs: DataFrame, path: str, ranks_path: str | None = None, end_id: int = 2, capacity: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces of all documents with ``sequence_id`` and ``offset``."""
    pieces = settle(tokenised(docs, path, ranks_path, end_id, capacity, id_col, text_col), "pieces")
    counts = {int(r[0]): int(r[1]) for r in pieces.groupBy("length").count().collect()}  # a row a length
    table, _ = plan(counts, capacity)
    before, total = {}, 0
    for k in sorted(counts):
        before[k] = total
        total += counts[k]
    order, _ = ranked(pieces, ["length", "doc_id", "piece", "start"], "pack_order")
    return order.mapInArrow(lambda it: place_batches(it, table, before), PLACED)


def public_paths() -> tuple[str, str]:
    import public_tokenizers

    return str(public_tokenizers.path("byte_bpe_50k.json")), str(public_tokenizers.path("byte_bpe_50k.tiktoken"))


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return pack(docs, *public_paths())
