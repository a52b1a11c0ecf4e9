"""Embedding near-duplicates by an inverted multi-index.

Two codebooks, one for each half of the unit vectors, form a product grid of cells; every vector is
listed in its nearest cell. A vector visits cells in multi-sequence order (growing sum of both halves'
squared distances) until the sum exceeds its smallest by a slack. The slack is set so that of probe
pairs at exactly the threshold the target share is found from either side; every vector found is then
verified by its cosine in double precision. Codebooks and slack are fitted on at most SAMPLE vectors;
all vectors are indexed and all visit. The codebooks grow with the vectors a label holds, so that a cell
lists about CELL_ROWS of them, up to SAMPLE / 16 codes a half (some 800 million vectors a label); beyond
that cells grow and are cut into more tiles.

Vectors compare within equal labels and lengths only. Lengths of which there are under FEW vectors are
too few to fit an index on: they meet in one cell for each label and length, in tiles, so exactly.
A cell with over TILE visitors is split into tiles, and its pairs of tiles are separate tasks. A task
returns counts and a spanning forest, never the pairs.

Nulls and odd input: vectors that are null, empty, zero, or hold null or non-finite components, and
vectors without a label, link with nothing; rows of one vec_id are one vector (a valid one before the
others, then the smallest by label and components); each row with a null vec_id stays a row of its own,
unlinked and kept, with component_id null; an empty table gives an empty result; other columns are
not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType

from meshprofile.llm.common import Forest, bounded_batches, components, materialise, table

COSINE, TARGET, SAMPLE, TILE, CELL_ROWS, FEW = 0.98, 0.999, 20_000, 2048, 512, 2048


def k_means(x: np.ndarray, k: int, rounds: int = 12, seed: int = 3) -> np.ndarray:
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)]
    for _ in range(rounds):
        near = (x @ c.T * 2 - (c * c).sum(1)).argmax(1)
        n = np.bincount(near, minlength=len(c))
        s = np.zeros_like(c)
        np.add.at(s, near, x)
        c = np.where(n[:, None] > 0, s / np.maximum(n, 1)[:, None], c)
    return c


class MultiIndex:
    def __init__(self, sample: np.ndarray, codes: int, cosine: float = COSINE, target: float = TARGET, seed: int = 3):
        x = sample / np.linalg.norm(sample, axis=1, keepdims=True)
        self.cut = x.shape[1] // 2 if x.shape[1] > 1 else 1
        self.halves = k_means(x[:, : self.cut], codes), k_means(x[:, self.cut :], codes)
        rng = np.random.default_rng(seed)
        a = x[rng.integers(0, len(x), 4000)]
        noise = rng.normal(size=a.shape)
        noise -= (noise * a).sum(1, keepdims=True) * a
        size = np.linalg.norm(noise, axis=1, keepdims=True)
        b = cosine * a + np.sqrt(1 - cosine**2) * noise / np.where(size > 0, size, 1)
        b /= np.linalg.norm(b, axis=1, keepdims=True)
        (a1, a2), (b1, b2) = self.distances(a), self.distances(b)
        row = np.arange(len(a))
        over = lambda p, q, i, j: p[row, i] - p.min(1) + q[row, j] - q.min(1)
        gap = np.minimum(over(a1, a2, b1.argmin(1), b2.argmin(1)), over(b1, b2, a1.argmin(1), a2.argmin(1)))
        self.slack = float(np.quantile(gap, target)) + 1e-9

    def distances(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Squared distances of the halves of unit vectors to the codes of each half."""
        return tuple((p * p).sum(1)[:, None] - 2 * p @ c.T + (c * c).sum(1) for p, c in zip((x[:, : self.cut], x[:, self.cut :]), self.halves))

    def visits(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Cells each unit vector visits, end to end, and n + 1 offsets: its own first, then by growing cost up to the slack.

        The frontier moves down the first half's sorted codes; at each, every vector that still has a cell
        within its slack takes the second half's codes that fit."""
        a, b = self.distances(x)
        oa, ob = np.argsort(a, 1, kind="stable"), np.argsort(b, 1, kind="stable")
        a, b = np.take_along_axis(a, oa, 1), np.take_along_axis(b, ob, 1)
        a, b = a - a[:, :1], b - b[:, :1]
        row, cell, cost = [], [], []
        for first in range(a.shape[1]):
            near = np.flatnonzero(a[:, first] <= self.slack)
            if not len(near):
                break
            fits = b[near] <= self.slack - a[near, first][:, None]
            i, second = np.nonzero(fits)
            i = near[i]
            row.append(i)
            cell.append(oa[i, first] * b.shape[1] + ob[i, second])
            cost.append(a[i, first] + b[i, second])
        row, cell, cost = (np.concatenate(v) if v else np.zeros(0) for v in (row, cell, cost))
        order = np.lexsort((cost, row))
        return cell[order].astype(np.int64), np.r_[0, np.cumsum(np.bincount(row.astype(np.int64), minlength=len(x)))]


def vectors_of(column: pa.Array) -> np.ndarray:
    """Rows of an array column of equal lengths, without nulls, in double precision."""
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 1))


def visits_column(index: MultiIndex, vector: str):
    @F.arrow_udf(ArrayType(LongType()))
    def visits(v: pa.Array) -> pa.Array:
        x = vectors_of(v)
        if not len(x):
            return pa.array([], pa.list_(pa.int64()))
        parts = [index.visits(p / np.linalg.norm(p, axis=1, keepdims=True)) for p in (x[i : i + 2048] for i in range(0, len(x), 2048))]
        sizes = np.concatenate([np.diff(ends) for _, ends in parts])
        return pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(sizes)].astype(np.int32)), pa.array(np.concatenate([c for c, _ in parts])))

    return visits(F.col(vector))


def links_of(vec: np.ndarray, ids: np.ndarray, listed: np.ndarray, tile: np.ndarray, home: np.ndarray, seen: np.ndarray, cells: int, cell: int, apart: bool, cosine: float) -> tuple[np.ndarray, np.ndarray]:
    """Links of each row of one task and its root. listed: rows the cell lists in this task; seen: sorted
    row * cells + cell of what the rows visit; apart: visitors come from another tile, so listed rows do
    not meet each other here."""
    unit = vec / np.linalg.norm(vec, axis=1, keepdims=True)
    forest, count = Forest(len(ids)), np.zeros(len(ids), np.int64)
    d, visitors = np.flatnonzero(listed), np.flatnonzero(~listed) if apart else np.arange(len(ids))
    for at in range(0, len(visitors), 512):
        q = visitors[at : at + 512]
        a, b = np.nonzero(unit[q] @ unit[d].T >= cosine)
        a, b = q[a], d[b]
        # both listed here: each pair once; a visitor from another cell: here if that cell's task does not see the pair
        own = home[a] == cell
        key = b * cells + home[a]
        spot = np.minimum(np.searchsorted(seen, key), len(seen) - 1)
        once = np.where(own, (tile[a] > tile[b]) | ((tile[a] == tile[b]) & (a > b)), (home[a] > cell) | (seen[spot] != key))
        keep = once & (ids[a] != ids[b])
        a, b = a[keep], b[keep]
        np.add.at(count, a, 1)
        np.add.at(count, b, 1)
        forest.link(a, b)
    return count, forest.root


def _tasks(cosine: float, cells: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def solve(rows: pa.Table) -> Iterator[pa.RecordBatch]:
            key = [rows.column(c).to_numpy() for c in ("grp", "cell", "ti", "tj")]
            cuts = np.r_[0, np.flatnonzero(np.logical_or.reduce([k[1:] != k[:-1] for k in key])) + 1, rows.num_rows]
            for a, b in zip(cuts[:-1], cuts[1:]):
                if b - a < 2:
                    continue
                part = rows.slice(a, b - a).combine_chunks()
                ids, tile, home, listed = (part.column(c).to_numpy() for c in ("vec_id", "tile", "home", "listed"))
                if not listed.any():
                    continue
                lists = part.column("visits").combine_chunks()
                seen = np.sort(np.repeat(np.arange(b - a), np.diff(lists.offsets.to_numpy())) * cells + lists.flatten().to_numpy())
                n, root = links_of(vectors_of(part.column("vector").combine_chunks()), ids, listed, tile, home, seen, cells, int(key[1][a]), bool(key[2][a] != key[3][a]), cosine)
                got = np.flatnonzero(n)
                yield pa.record_batch([pa.array(ids[got]), pa.array(n[got]), pa.array(ids[root[got]])], names=["a", "n", "b"])

        for batch in batches:
            held.append(batch)
            if sum(x.num_rows for x in held) < 1 << 13:
                continue
            rows = pa.Table.from_batches(held)
            keys = [rows.column(c).to_numpy() for c in ("grp", "cell", "ti", "tj")]
            ends = np.flatnonzero(np.logical_or.reduce([k[1:] != k[:-1] for k in keys]))
            if len(ends):
                cut = int(ends[-1]) + 1
                yield from solve(rows.slice(0, cut))
                held = rows.slice(cut).to_batches()
        if held:
            yield from solve(pa.Table.from_batches(held))

    return run


def indexed(vectors: DataFrame, cosine: float, target: float) -> tuple[DataFrame, int]:
    """vectors, all of one length, with the cells they visit and their home cell; the number of cells."""
    total = vectors.agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct("grp").alias("k")).first()
    sample = np.array([r[0] for r in vectors.orderBy(F.xxhash64("vec_id")).limit(SAMPLE).select("vector").collect()], np.float64)
    codes = int(np.clip(round((total["n"] / max(1, total["k"]) / CELL_ROWS) ** 0.5), 2, max(2, SAMPLE // 16)))
    index = MultiIndex(sample, codes, cosine, target)
    return vectors.withColumn("visits", visits_column(index, "vector")).withColumn("home", F.col("visits")[0]), len(index.halves[0]) * len(index.halves[1])


def embedding_links(vectors: DataFrame, cosine: float = COSINE, target: float = TARGET) -> tuple[DataFrame, DataFrame]:
    """From (vec_id, grp, dim, vector) rows, all valid, grp naming label and length: link counts (a, n) and edges (a, b)."""
    bounded_batches()
    dims = vectors.groupBy("dim").count()
    many = sorted(r["dim"] for r in dims.where(F.col("count") >= FEW).collect())  # at most rows / FEW
    rest = vectors.where(~F.col("dim").isin(many)) if many else vectors
    parts = [(vectors.where(F.col("dim") == d), True) for d in many] + [(rest, False)]
    counts, edges = [], []
    for part, large in parts:
        spread, cells = indexed(part, cosine, target) if large else (part.withColumn("visits", F.array(F.lit(0).cast("long"))).withColumn("home", F.lit(0).cast("long")), 1)
        found = _links_in_cells(spread.drop("dim"), cells, cosine)
        counts.append(found.groupBy("a").agg(F.sum("n").alias("n")))
        edges.append(found.select("a", "b"))
    return reduce(DataFrame.unionByName, counts), reduce(DataFrame.unionByName, edges)


def _links_in_cells(rows: DataFrame, cells: int, cosine: float) -> DataFrame:
    listed = materialise(rows, "multi-index")
    slim = listed.select("grp", F.explode("visits").alias("cell"))
    hot = slim.groupBy("grp", "cell").count().where(F.col("count") > TILE).select("grp", "cell", F.ceil(F.col("count") / TILE).cast("int").alias("tiles"))
    spread = listed.withColumn("cell", F.explode("visits")).join(hot, ["grp", "cell"], "left").withColumn("tiles", F.coalesce("tiles", F.lit(1)))
    spread = spread.withColumn("tile", F.expr("cast(pmod(xxhash64(vec_id, 5), tiles) as int)"))
    # a listed row meets every visitor tile at or after its own; a row visits every list tile (its own cell's only below its own)
    spread = spread.withColumn(
        "task",
        F.explode(
            F.expr(
                "if(home = cell, concat(transform(sequence(tile, tiles - 1), j -> named_struct('ti', tile, 'tj', j, 'listed', true)), transform(filter(sequence(0, tiles - 1), i -> i < tile), i -> named_struct('ti', i, 'tj', tile, 'listed', false))),"
                " transform(sequence(0, tiles - 1), i -> named_struct('ti', i, 'tj', tile, 'listed', false)))"
            )
        ),
    ).select("grp", "cell", "task.*", "vec_id", "vector", "visits", "home", "tile")
    # listed rows also receive visitors of other cells whose tile is before theirs
    back = spread.where("listed and ti = tj").join(hot, ["grp", "cell"]).withColumn("tj", F.explode(F.expr("filter(sequence(0, tiles - 1), j -> j < ti)"))).drop("tiles").select(spread.columns)
    key = ["grp", "cell", "ti", "tj"]
    return materialise(spread.unionByName(back).repartition(*key).sortWithinPartitions(*key).mapInArrow(_tasks(cosine, cells), "a long, n long, b long"), "embedding-links")


def near_vectors(rows: DataFrame, cosine: float = COSINE, target: float = TARGET) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of rows (vec_id, embedding, label)."""
    bad = "exists(embedding, x -> x is null or isnan(x) or abs(x) = double('inf')) or not exists(embedding, x -> x <> 0)"
    valid = F.coalesce(F.expr(f"label is not null and embedding is not null and size(embedding) > 0 and not ({bad})"), F.lit(False))
    best = F.min(F.struct((~valid).alias("bad"), "label", "embedding")).alias("s")
    one = rows.where("vec_id is not null").groupBy("vec_id").agg(best)
    one = materialise(one.select("vec_id", (~F.col("s.bad")).alias("valid"), F.col("s.label").cast("long").alias("label"), F.col("s.embedding").alias("vector")), "vectors")
    sized = one.where("valid").select("vec_id", "vector", F.size("vector").alias("dim"), F.expr("shiftleft(label, 32) + size(vector)").alias("grp"))
    counts, edges = embedding_links(sized, cosine, target)
    label = components(edges, "embedding").select(F.col("node").alias("vec_id"), F.col("component").alias("component_id"))
    out = one.select("vec_id").join(counts.select(F.col("a").alias("vec_id"), F.col("n").alias("n_links")), "vec_id", "left").join(label, "vec_id", "left")
    out = out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    nameless = rows.where("vec_id is null").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return out.unionByName(nameless).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def op9_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_vectors(table(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label"))


QUERIES = {"op9_embedding_dedup": op9_embedding_dedup}
ORACLES = {}
