"""Token packing for training: best-fit-decreasing into rows of fixed length.

Each document is encoded, closed by an end token and, if longer than a row, split into pieces that keep
their place (nothing is dropped). Pieces of a group (about GROUP tokens from one task, so no shuffle)
are sorted by length and each goes to the row whose free space fits it best, found by descending a
segment tree over free-space values. Rows hold the id matrix (int32, little-endian, padded), cumulative
segment lengths, positions that restart at each piece, and each piece's document and offset.

Nulls and odd input: null and empty texts are one end token; a null doc_id stays null in doc_ids;
repeated rows are packed each; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshprofile.llm.bpe import encoder, model_path
from meshprofile.llm.common import bounded_batches, table, text_chunks

LENGTH, GROUP, END = 2048, 1 << 21, 50256
PACKED = "pack_id string, n_tokens int, doc_ids array<long>, offsets array<long>, cu_seqlens array<int>, input_ids binary, position_ids binary"


class SpaceTree:
    """Rows by free space: a segment tree over the values 0..length that counts rows with each."""

    def __init__(self, length: int):
        self.half = 1 << length.bit_length()
        self.n = [0] * (2 * self.half)
        self.rows: list[list[int]] = [[] for _ in range(length + 1)]

    def add(self, free: int, row: int, by: int = 1) -> None:
        i = free + self.half
        while i:
            self.n[i] += by
            i >>= 1
        if by > 0:
            self.rows[free].append(row)

    def take(self, need: int) -> tuple[int, int] | None:
        """(free space, row) of the fullest row with at least `need` free, removed; None if none has."""
        i = need + self.half
        if not self.n[i]:
            while i > 1 and (i & 1 or not self.n[i + 1]):
                i >>= 1
            if i == 1:
                return None
            i += 1
            while i < self.half:
                i *= 2
                if not self.n[i]:
                    i += 1
        free = i - self.half
        self.add(free, 0, -1)
        return free, self.rows[free].pop()


def best_fit_decreasing(sizes: np.ndarray, length: int = LENGTH) -> list[list[int]]:
    """Rows of piece numbers; every size is 1..length."""
    tree, rows = SpaceTree(length), []
    for i in np.argsort(-sizes, kind="stable").tolist():
        need = int(sizes[i])
        got = tree.take(need)
        free, row = got if got else (length, len(rows))
        if got is None:
            rows.append([])
        rows[row].append(i)
        tree.add(free - need, row)
    return rows


def _pack(path: str, length: int, end: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, at = TaskContext.get().partitionId(), 0
        ids: list[np.ndarray] = []
        of: list[tuple[int | None, int]] = []
        names = [c.split()[0] for c in PACKED.split(", ")]

        def flush() -> pa.RecordBatch:
            nonlocal at
            cols: list[list] = [[] for _ in names]
            for row in best_fit_decreasing(np.array([len(x) for x in ids]), length):
                n = np.array([len(ids[i]) for i in row])
                tokens = np.full(length, end, np.int32)
                tokens[: n.sum()] = np.concatenate([ids[i] for i in row])
                spots = np.zeros(length, np.int32)
                spots[: n.sum()] = np.concatenate([np.arange(k) for k in n])
                for c, v in zip(cols, (f"{task}-{at}", n.sum(), [of[i][0] for i in row], [of[i][1] for i in row], np.r_[0, np.cumsum(n)].astype(np.int32), tokens.tobytes(), spots.tobytes())):
                    c.append(v)
                at += 1
            ids.clear()
            of.clear()
            kinds = (pa.string(), pa.int32(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.int32()), pa.binary(), pa.binary())
            return pa.record_batch([pa.array(c, k) for c, k in zip(cols, kinds)], names=names)

        held = 0
        for batch, texts in text_chunks(batches):
            flat, ends = encoder(path).encode(texts)
            for doc, a, b in zip(batch.column("doc_id").to_pylist(), ends[:-1].tolist(), ends[1:].tolist()):
                own = np.r_[flat[a:b], end].astype(np.int32)
                for start in range(0, len(own), length):
                    ids.append(own[start : start + length])
                    of.append((doc, start))
                held += len(own)
                if held >= GROUP:
                    yield flush()
                    held = 0
        if ids:
            yield flush()

    return run


def pack_documents(docs: DataFrame, length: int = LENGTH, path: str | None = None, end: int = END) -> DataFrame:
    """Packed rows (PACKED) of docs (doc_id, text); pack_id tells task and row."""
    bounded_batches()
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_pack(path or model_path(), length, end), PACKED)


def write_packed(packed: DataFrame, path: str) -> None:
    """Write packed rows to a shared folder: Parquet with the matrices as binary columns."""
    packed.write.mode("errorifexists").parquet(path)


def op1_pack_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every packed row with SHA-256 digests in place of its matrices."""
    packed = pack_documents(table(spark, sf_dir, "documents"))
    return packed.select("pack_id", "n_tokens", "doc_ids", "offsets", "cu_seqlens", F.sha2("input_ids", 256).alias("ids_sha256"), F.sha2("position_ids", 256).alias("positions_sha256"))


QUERIES = {"op1_pack_tokens": op1_pack_tokens}
ORACLES = {}
