"""SimHash near-duplicates by a Gray-order hierarchical index.

Fingerprints: majority bits of the XXH64 (seed 42) of all 3-word shingles, repeats included. Two
fingerprints link at 3 or fewer differing bits. Of four rotations by 16 bits, at least one brings an
equal leading block of 16 bits to any such pair; within a block, fingerprints are sorted by their
Gray rank, runs of them form leaves and runs of leaves upper nodes, each holding the bits its members
share. The join walks pairs of nodes downwards; the differences among shared bits add up on the way
and a pair of groups over 3 is dropped whole. Blocks over TILE rows are salted into pairs of tiles, so
no task holds more than two tiles of a block; links leave a task as a spanning forest, never as pairs.

Nulls and odd input: a null text is empty; texts without a word have fingerprint zero and link like
any other; a null doc_id takes part, and a component of nulls only has component_id null; repeated
rows stay repeated; an empty table gives an empty result; other columns pass unread (columns named
_id, _h or _n are dropped from survivors).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from meshprofile.llm.common import Forest, bounded_batches, components, flat_bytes, materialise, table, text_chunks

BITS, BLOCKS, FAR, SHINGLE, SEED = 64, 4, 3, 3, 42
TILE, RUN, PAIRS = 4096, 8, 1 << 20


def fingerprints(texts: pa.Array) -> np.ndarray:
    """uint64 fingerprint of each text (large_string, no nulls)."""
    lists = pc.ascii_split_whitespace(pc.ascii_lower(texts))
    words = lists.flatten()
    size = pc.binary_length(words).to_numpy(zero_copy_only=False).astype(np.int64)
    doc = np.repeat(np.arange(len(texts)), np.diff(lists.offsets.to_numpy()))[size > 0]
    words, size = words.filter(pa.array(size > 0)), size[size > 0]
    out = np.zeros(len(texts), np.uint64)
    if not len(words):
        return out
    # one space after each word: a shingle is one slice
    spaced = pc.binary_join_element_wise(words, pa.scalar("", pa.large_string()), pa.scalar(" ", pa.large_string()))
    raw, starts = flat_bytes(spaced.cast(pa.large_string()))
    ends = starts[1:] - 1
    n = np.bincount(doc, minlength=len(texts))
    first = np.cumsum(n) - n
    last = np.minimum(np.arange(len(words)) + SHINGLE - 1, (first + n - 1)[doc])
    head = (np.arange(len(words)) + SHINGLE - 1 <= (first + n - 1)[doc]) | (np.arange(len(words)) == first[doc])
    data, digest = raw.tobytes(), xxhash.xxh64_intdigest
    s, e, owner = starts[:-1][head], ends[last[head]], doc[head]
    hashes = np.fromiter((digest(data[a:b], SEED) for a, b in zip(s.tolist(), e.tolist())), np.uint64, len(s))
    cuts = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
    total = np.diff(np.r_[cuts, len(owner)])
    weights = np.uint64(1) << np.arange(BITS, dtype=np.uint64)
    bits = np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    counts = np.stack([bits[a:b].sum(0, dtype=np.int32) for a, b in zip(cuts, np.r_[cuts[1:], len(owner)])])
    out[owner[cuts]] = ((2 * counts > total[:, None]) * weights).sum(1, dtype=np.uint64)
    return out


@F.arrow_udf(LongType())
def fingerprint_udf(text: pa.Array) -> pa.Array:
    batch = pa.record_batch([text], names=["text"])
    parts = [fingerprints(t).view(np.int64) for _, t in text_chunks(iter([batch]))]
    return pa.array(np.concatenate(parts) if parts else np.zeros(0, np.int64))


def gray_rank(x: np.ndarray) -> np.ndarray:
    """Position of x in Gray order: each bit is the parity of the bits at or above it."""
    for shift in (1, 2, 4, 8, 16, 32):
        x = x ^ (x >> np.uint64(shift))
    return x


class GrayIndex:
    """Nodes over fingerprints sorted by (group, Gray rank): levels of shared-bit patterns."""

    def __init__(self, group: np.ndarray, value: np.ndarray):
        self.levels = [(value, np.full(len(value), ~np.uint64(0)), None, None)]  # pattern, shared bits, first child, children
        owner = group
        while True:
            new = np.r_[True, owner[1:] != owner[:-1]]
            place = np.arange(len(owner)) - np.maximum.accumulate(np.where(new, np.arange(len(owner)), 0))
            first = np.flatnonzero(new | (place % RUN == 0))
            n = np.diff(np.r_[first, len(owner)])
            pattern, shared = self.levels[-1][:2]
            differ = np.bitwise_or.reduceat((pattern ^ np.repeat(pattern[first], n)) | ~shared, first)
            self.levels.append((pattern[first], ~differ, first, n))
            owner = owner[first]
            if len(np.unique(owner)) == len(owner):
                return

    def links(self, far: int = FAR) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs of rows i < j of one group that differ in at most far bits; work is cut into bounded pieces."""
        top = np.arange(len(self.levels[-1][0]))
        todo = [(len(self.levels) - 1, top, top)]
        while todo:
            level, i, j = todo.pop()
            if level == 0:
                yield i, j
                continue
            _, _, first, n = self.levels[level]
            size = n[i] * n[j]
            if size.sum() > PAIRS and len(i) > 1:
                half = len(i) // 2
                todo += [(level, i[:half], j[:half]), (level, i[half:], j[half:])]
                continue
            of = np.repeat(np.arange(len(i)), size)
            k = np.arange(len(of)) - np.repeat(np.cumsum(size) - size, size)
            a, b = first[i][of] + k // n[j][of], first[j][of] + k % n[j][of]
            keep = a < b if level == 1 else a <= b
            a, b = a[keep], b[keep]
            pattern, shared = self.levels[level - 1][:2]
            near = np.bitwise_count((pattern[a] ^ pattern[b]) & shared[a] & shared[b]) <= far
            if near.any():
                todo.append((level - 1, a[near], b[near]))


def _forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (task key, Gray rank) -> spanning edges (a, b) of the links in each key."""
    held: list[pa.RecordBatch] = []

    def solve(rows: pa.Table) -> Iterator[pa.RecordBatch]:
        if rows.num_rows < 2:
            return
        value, tile, apart, *key = (rows.column(c).to_numpy() for c in ("fp", "tile", "apart", "rot", "block", "ti", "tj"))
        group = np.cumsum(np.r_[0, np.logical_or.reduce([k[1:] != k[:-1] for k in key])])
        forest = Forest(len(value))
        for i, j in GrayIndex(group, value.view(np.uint64)).links():
            keep = ~apart[i] | (tile[i] != tile[j])
            forest.link(i[keep], j[keep])
        moved = np.flatnonzero(forest.root != np.arange(len(value)))
        yield pa.record_batch([pa.array(value[moved]), pa.array(value[forest.root[moved]])], names=["a", "b"])

    for batch in batches:
        held.append(batch)
        if sum(b.num_rows for b in held) < 1 << 16:
            continue
        rows = pa.Table.from_batches(held)
        keys = [rows.column(c).to_numpy() for c in ("rot", "block", "ti", "tj")]
        ends = np.flatnonzero(np.logical_or.reduce([k[1:] != k[:-1] for k in keys]))
        if len(ends):
            cut = int(ends[-1]) + 1
            yield from solve(rows.slice(0, cut))
            held = rows.slice(cut).to_batches()
    if held:
        yield from solve(pa.Table.from_batches(held))


def fingerprint_components(fps: DataFrame) -> DataFrame:
    """Distinct fp (long) -> (node, component) for those with a link."""
    spots = fps.select("fp", F.explode(F.sequence(F.lit(0), F.lit(BLOCKS - 1))).alias("rot")).withColumn(
        "turned", F.expr("if(rot = 0, fp, shiftleft(fp, 16 * rot) | shiftrightunsigned(fp, 64 - 16 * rot))")
    )
    rank = "turned"
    for shift in (1, 2, 4, 8, 16, 32):
        spots = spots.withColumn("_r", F.expr(f"{rank} ^ shiftrightunsigned({rank}, {shift})")).drop(*(["rank"] if rank == "rank" else [])).withColumnRenamed("_r", "rank")
        rank = "rank"
    spots = spots.withColumn("block", F.expr("shiftrightunsigned(turned, 48)")).drop("turned")
    hot = spots.groupBy("rot", "block").count().where(F.col("count") > TILE).select("rot", "block", F.ceil(F.col("count") / TILE).cast("int").alias("tiles"))
    dealt = (
        spots.join(hot, ["rot", "block"], "left")
        .withColumn("tiles", F.coalesce("tiles", F.lit(1)))
        .withColumn("tile", F.expr("cast(pmod(xxhash64(fp), tiles) as int)"))
        .withColumn("other", F.explode(F.expr("sequence(0, tiles - 1)")))
        .select("fp", "rot", "block", "rank", "tile", F.least("tile", "other").alias("ti"), F.greatest("tile", "other").alias("tj"))
        .withColumn("apart", F.col("ti") != F.col("tj"))
    )
    key = ["rot", "block", "ti", "tj"]
    # unsigned order of the rank within the key
    sorted_ = dealt.repartition(*key).sortWithinPartitions(*key, F.expr("rank ^ (-9223372036854775807 - 1)"))
    return components(sorted_.mapInArrow(_forest, "a long, b long"), "simhash")


def simhash_groups(docs: DataFrame, *also: str) -> DataFrame:
    """(doc_id, fp, component, component_id) of every row of docs, and the columns of docs named in also;
    component, a fingerprint, names the group even where all its ids are null."""
    bounded_batches()
    prints = materialise(docs.select("doc_id", *also, fingerprint_udf("text").alias("fp")), "fingerprints")
    least = prints.groupBy("fp").agg(F.min("doc_id").alias("least"))
    label = fingerprint_components(least.select("fp")).select(F.col("node").alias("fp"), "component")
    named = materialise(least.join(label, "fp", "left").select("fp", "least", F.coalesce("component", "fp").alias("component")), "simhash-named")
    root = named.groupBy("component").agg(F.min("least").alias("component_id"))
    return prints.join(named.join(root, "component").select("fp", "component", "component_id"), "fp")


def simhash_survivors(docs: DataFrame) -> DataFrame:
    """Rows of docs, all columns: of each component one row, that with the smallest doc_id (a null one last, then by the
    text's hash; of rows alike in both, the least by the hash of their other columns). Rows are chosen by id and text
    hash without their texts; texts cross one exchange, which the join and the last choice share."""
    row = [c for c, kind in docs.dtypes if c not in ("text", "doc_id", "_id", "_h", "_n") and "map<" not in kind]
    keyed = docs.drop("_id", "_h", "_n").withColumns({"_id": F.coalesce("doc_id", F.lit(0)), "_h": F.xxhash64(F.isnull("doc_id"), "text")})
    chosen = simhash_groups(keyed, "_id", "_h").groupBy("component").agg(F.min(F.struct(F.isnull("doc_id"), "doc_id", "_h", "_id")).alias("s"))
    found = keyed.join(chosen.select("s._id", "s._h"), ["_id", "_h"])
    order = F.xxhash64(*[F.col(c) for c in row]) if row else F.lit(0)
    one = found.withColumn("_n", F.row_number().over(Window.partitionBy("_id", "_h").orderBy(order)))
    return one.where("_n = 1").select(*[c for c in docs.columns if c not in ("_id", "_h", "_n")])


def op10_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash_groups(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


QUERIES = {"op10_simhash_dedup": op10_simhash_dedup}
ORACLES = {}
