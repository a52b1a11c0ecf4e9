"""Shared pieces: word rule, shared folder, bounded text chunks, connected components."""

from __future__ import annotations

import ctypes
import re
import sys
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a run of anything but space and U+0009..U+000D.
WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"
GAP_CHARS = " \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share; where none is set, a local one in a session of one process, else an error."""
    sc = spark.sparkContext
    got = spark.conf.get("spark.checkpoint.dir", None) or sc._jsc.sc().getCheckpointDir().getOrElse(None)
    if not got:
        if not re.fullmatch(r"local(\[[^]]*\])?", sc.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        got = tempfile.mkdtemp(prefix="shared-")
        sc.setCheckpointDir(got)
        got = sc._jsc.sc().getCheckpointDir().get()
    return got.rstrip("/")


_written: list[str] = []


def shared_tables() -> int:
    """How many tables this driver has written to the shared folder and not deleted."""
    return len(_written)


def clear_shared(spark: SparkSession, since: int = 0, keep: int = 0) -> int:
    """Delete the tables that this driver has written to the shared folder, from the `since`-th on but for the last
    `keep`; call it once results that read them are stored. Gives their number."""
    old = _written[since : len(_written) - keep]
    del _written[since : len(_written) - keep]
    for name in old:
        path = spark._jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    return len(old)


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write df to the shared folder and read it back: lineage is cut, lost executors cost nothing."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    _written.append(path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def words_of(text):
    """Column: array of the words of a text; null gives an empty array. btrim and split stay in the JVM."""
    core = F.btrim(F.coalesce(text, F.lit("")), F.lit(GAP_CHARS))
    return F.when(core == "", F.array().cast("array<string>")).otherwise(F.split(core, GAP))


def bounded_batches(most: int = 4 << 20) -> None:
    """Hold the session's Arrow batches to so many bytes: rows of texts differ a thousandfold in size."""
    spark = SparkSession.active()
    if not 0 < int(str(spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch")).rstrip("b")) <= most:
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(most))


def give_back() -> None:
    """Return freed memory of Arrow and malloc to the system: a worker serves many stages in turn."""
    pa.default_memory_pool().release_unused()
    if sys.platform == "linux":
        ctypes.CDLL(None).malloc_trim(0)


def keep_small() -> None:
    """Let malloc keep up to 32 MB of freed memory and serve blocks below 8 MB from it: batch after batch needs the same
    blocks, and pages that are given back and fetched again can cost as much as the work on them. give_back still empties it."""
    if sys.platform == "linux":
        libc = ctypes.CDLL(None)
        libc.mallopt(-3, 8 << 20)  # M_MMAP_THRESHOLD
        libc.mallopt(-1, 32 << 20)  # M_TRIM_THRESHOLD


def text_chunks(batches: Iterator[pa.RecordBatch], column: str = "text", most: int = 1 << 20) -> Iterator[tuple[pa.RecordBatch, pa.Array]]:
    """Slices of the batches whose text is at most `most` bytes (one longer text stands alone), with null texts as empty ones."""
    for batch in batches:
        if not batch.num_rows:
            continue
        texts = pc.fill_null(batch.column(batch.schema.get_field_index(column)).cast(pa.large_string()), "")
        ends = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False).astype(np.int64))
        at = 0
        while at < batch.num_rows:
            base = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, base + most, "right")))
            yield batch.slice(at, to - at), _rebased(texts.slice(at, to - at))
            at = to
        give_back()


def _rebased(texts: pa.Array) -> pa.Array:
    """The same texts with offsets from zero: some Arrow kernels misread arrays whose bytes start later."""
    offsets = np.frombuffer(texts.buffers()[1], np.int64, len(texts) + 1, texts.offset * 8)
    data = texts.buffers()[2]
    if data is None:
        return texts
    own = data.slice(int(offsets[0]), int(offsets[-1] - offsets[0]))
    return pa.LargeStringArray.from_buffers(len(texts), pa.py_buffer(offsets - offsets[0]), own)


def flat_bytes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Concatenated bytes of a large_string array and its n + 1 offsets, from zero."""
    offsets = np.frombuffer(texts.buffers()[1], np.int64, len(texts) + 1, texts.offset * 8)
    data = texts.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def components(edges: DataFrame, name: str = "components") -> DataFrame:
    """Connected components of edges(a, b): rows (node, component), component the smallest node.

    Every round hooks each node on its smallest neighbour, follows pointers twice and relabels the
    edges; the edges left between different roots are written to the shared folder, so lineage stays
    flat and no graph part is held by the driver. Nodes without an edge have no row. Hot nodes are
    join keys only in equi-joins, which adaptive execution splits.
    """
    spark = edges.sparkSession
    edges = materialise(
        edges.where("a is not null and b is not null and a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), name
    )
    label = None
    while not edges.isEmpty():
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        hook = both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("p")).select(F.col("a").alias("n"), "p")
        for step in range(3):
            up = hook.select(F.col("n").alias("p"), F.col("p").alias("q"))
            hook = hook.join(up, "p", "left").select("n", F.coalesce("q", "p").alias("p"))
            if step == 0:
                hook = materialise(hook, name)
        hook = materialise(hook, name)
        if label is None:
            label = hook
        else:
            # labels are roots of the last round: only those still on an edge move
            label = materialise(label.join(hook.select(F.col("n").alias("p"), F.col("p").alias("q")), "p", "left").select("n", F.coalesce("q", "p").alias("p")), name)
        left = edges.join(hook.select(F.col("n").alias("a"), F.col("p").alias("pa")), "a").join(hook.select(F.col("n").alias("b"), F.col("p").alias("pb")), "b")
        edges = materialise(left.where("pa <> pb").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).distinct(), name)
    if label is None:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).limit(0)
    return label.select(F.col("n").alias("node"), F.col("p").alias("component"))


class Forest:
    """Union-find over 0..n-1 with vectorised hooking, for the links found inside one task."""

    def __init__(self, n: int):
        self.root = np.arange(n)

    def link(self, a: np.ndarray, b: np.ndarray) -> None:
        root = self.root
        while len(a):
            ra, rb = root[a], root[b]
            keep = ra != rb
            a, b, ra, rb = a[keep], b[keep], ra[keep], rb[keep]
            if not len(a):
                return
            np.minimum.at(root, np.maximum(ra, rb), np.minimum(ra, rb))
            while True:
                up = root[root]
                if np.array_equal(up, root):
                    break
                root = self.root = up
