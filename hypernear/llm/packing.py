"""Token ids packed into fixed-width rows: best-fit decreasing with a segment tree.

Each task tokenises its own documents and packs them in blocks of at most ``block_tokens`` ids, so nothing is
shuffled, memory is bounded, and a retried task writes the same rows. A document longer than a row is split into
row-sized pieces and a rest, losslessly; ``piece`` numbers them. Pieces go, longest first, into the fullest row
that still holds them, found by descending a segment tree over the free room.

Defined cases: null and empty texts have no ids and leave no segment; repeated rows are packed each; a null
doc_id stays null in ``doc_ids``; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import base64
import json
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.taskcontext import TaskContext

from .common import opened, ship

# Fixed value: how public byte-level vocabularies cut a text before merging.
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"
SCHEMA = "block string, row int, ids binary, n_tokens int, cu_seqlens array<int>, position_resets array<int>, doc_ids array<long>, pieces array<int>"


class FreeRoom:
    """How many open rows have each amount of free room, as a segment tree over 0..width.

    ``best(need)`` is the least room of at least ``need`` that some row has.
    """

    def __init__(self, width: int):
        self.leaves = 1 << width.bit_length()
        self.count = [0] * (2 * self.leaves)
        self.rows: list[list[int]] = [[] for _ in range(width + 1)]

    def add(self, room: int, row: int) -> None:
        self.rows[room].append(row)
        self._bump(room, 1)

    def take(self, room: int) -> int:
        self._bump(room, -1)
        return self.rows[room].pop()

    def _bump(self, room: int, by: int) -> None:
        at = room + self.leaves
        while at:
            self.count[at] += by
            at >>= 1

    def best(self, need: int) -> int | None:
        at = need + self.leaves
        if self.count[at]:
            return need
        while at > 1:  # up until a right sibling holds rows, then down its leftmost branch
            if not at & 1 and self.count[at + 1]:
                at += 1
                while at < self.leaves:
                    at = 2 * at + (not self.count[2 * at])
                return at - self.leaves
            at >>= 1
        return None


def pack(lengths: list[int], width: int) -> list[list[int]]:
    """Rows of piece numbers; every length is from 1 to width. Ties keep the given order."""
    rows: list[list[int]] = []
    room = FreeRoom(width)
    for piece in sorted(range(len(lengths)), key=lambda k: -lengths[k]):
        fit = room.best(lengths[piece])
        if fit is None:
            row, fit = len(rows), width
            rows.append([])
        else:
            row = room.take(fit)
        rows[row].append(piece)
        if fit > lengths[piece]:
            room.add(fit - lengths[piece], row)
    return rows


def tokenizer(ranks: dict[bytes, int]) -> Callable[[str], list[int]]:
    import tiktoken

    return tiktoken.Encoding("packing", pat_str=PIECES, mergeable_ranks=ranks, special_tokens={}).encode_ordinary


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in lines if line.strip())}


def pack_tokens(docs: DataFrame, vocabulary: str = VOCABULARY, width: int = 2048, block_tokens: int = 4_000_000) -> DataFrame:
    """Packed rows of all texts: ids as little-endian unsigned integers (2 bytes where the vocabulary allows,
    else 4), cumulative segment lengths, the offsets where positions start again from 0, and for each segment
    its document and piece. ``block`` and ``row`` name a row of a matrix.

    The vocabulary is read on the driver and broadcast: its size is that of the file, not of the data.
    """
    ranks = load_ranks(vocabulary)
    kind = "<u2" if max(ranks.values(), default=0) < 2**16 else "<u4"
    shipped = ship(docs.sparkSession, ranks)

    def emit(block: str, ids: list[np.ndarray], owners: list[tuple[int | None, int]]) -> Iterator[pa.RecordBatch]:
        rows = pack([len(x) for x in ids], width)
        for at in range(0, len(rows), 512):
            made = rows[at : at + 512]
            ends = [np.cumsum([0] + [len(ids[p]) for p in row]) for row in made]
            yield pa.RecordBatch.from_pydict({
                "block": pa.array([block] * len(made), pa.string()), "row": pa.array(range(at, at + len(made)), pa.int32()),
                "ids": pa.array([np.concatenate([ids[p] for p in row]).tobytes() for row in made], pa.binary()), "n_tokens": pa.array([int(e[-1]) for e in ends], pa.int32()),
                "cu_seqlens": pa.array([e.tolist() for e in ends], pa.list_(pa.int32())), "position_resets": pa.array([e[:-1].tolist() for e in ends], pa.list_(pa.int32())),
                "doc_ids": pa.array([[owners[p][0] for p in row] for row in made], pa.list_(pa.int64())), "pieces": pa.array([[owners[p][1] for p in row] for row in made], pa.list_(pa.int32())),
            })

    def run(batches):
        encode, part, block = tokenizer(opened(shipped)), TaskContext.get().partitionId(), 0
        ids, owners, held = [], [], 0
        for batch in batches:
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                whole = np.array(encode(text), dtype=kind) if text else ()
                for piece, at in enumerate(range(0, len(whole), width)):
                    ids.append(whole[at : at + width])
                    owners.append((doc_id, piece))
                held += len(whole)
                if held >= block_tokens:
                    yield from emit(f"{part}-{block}", ids, owners)
                    ids, owners, held, block = [], [], 0, block + 1
        if ids:
            yield from emit(f"{part}-{block}", ids, owners)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, SCHEMA)


def position_ids(cu_seqlens: list[int]) -> np.ndarray:
    """Positions of a packed row: each segment counts from 0."""
    ends = np.asarray(cu_seqlens)
    return np.arange(ends[-1]) - np.repeat(ends[:-1], np.diff(ends))


def write_matrices(packed: DataFrame, path: str, width: int, pad_id: int = 0, dtype: str = "<u2") -> DataFrame:
    """Write id matrices as Parquet, one file a task: each row's ids filled up to width with pad_id, n_tokens of them real, beside
    its segment bounds and resets; the settings stand beside the matrices."""

    def fill(batches):
        size = np.dtype(dtype).itemsize
        blank = np.array([pad_id], dtype=dtype).tobytes()
        at = packed_names.index("ids")
        for batch in batches:
            ids = [row + blank * (width - len(row) // size) for row in batch.column(at).to_pylist()]
            yield batch.set_column(at, "ids", pa.array(ids, pa.binary()))

    packed_names = packed.columns
    packed.mapInArrow(fill, packed.schema).write.mode("overwrite").option("compression", "zstd").parquet(f"{path}/matrix")
    spark: SparkSession = packed.sparkSession
    settings = json.dumps({"width": width, "pad_id": pad_id, "dtype": dtype})
    spark.createDataFrame([(settings,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/settings")
    return spark.read.parquet(f"{path}/matrix")


def unpack(packed: DataFrame, dtype: str = "<u2") -> DataFrame:
    """The pieces back as (doc_id, piece, ids): the inverse of packing, for exact round trips."""

    def run(batches):
        for batch in batches:
            out = {"doc_id": [], "piece": [], "ids": []}
            for ids, ends, docs, pieces in zip(*(batch.column(c).to_pylist() for c in ("ids", "cu_seqlens", "doc_ids", "pieces"))):
                row = np.frombuffer(ids, dtype)
                for k, (doc, piece) in enumerate(zip(docs, pieces)):
                    out["doc_id"].append(doc)
                    out["piece"].append(piece)
                    out["ids"].append(row[ends[k] : ends[k + 1]].tolist())
            yield pa.RecordBatch.from_pydict({"doc_id": pa.array(out["doc_id"], pa.int64()), "piece": pa.array(out["piece"], pa.int32()), "ids": pa.array(out["ids"], pa.list_(pa.int32()))})

    return packed.select("ids", "cu_seqlens", "doc_ids", "pieces").mapInArrow(run, "doc_id long, piece int, ids array<int>")

