"""Language-model scoring of whole texts, beside a smoothed unigram base.

Texts count as lower-case words. One pass turns chunks of documents (bounded in bytes, never across
tasks) into word indices over the chunk's own distinct words, with their training counts and the
chunk's subword bigram counts, kept as a table. Corpus counts come back to a chunk by one window over its
distinct words, so what is shuffled is distinct words per chunk, not words. A second pass scores every
document: the base from the counts of its words, the model by overlapping windows (see attention_lm).

Word counts, subword counts (which choose the codes) and bigram counts cover all training documents. The
network starts from a fit on the driver to at most SAMPLE of them; from there each task goes over every
window of the training texts of its chunks, long ones included, and the averaged result is the model.

Nulls and odd input: a null text is empty and has only its end; a null doc_id is not held out and
trains; repeated rows count and score each; an empty table gives an empty result; extra columns are
not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshprofile.llm import attention_lm as lm
from meshprofile.llm.bpe import encoder, model_path
from meshprofile.llm.common import bounded_batches, give_back, keep_small, materialise, table, text_chunks
from meshprofile.llm.learning import fold

SAMPLE, LONGEST, CHUNK = 3000, 20_000, 9 << 20
END = 50256  # the tokenizer file's end-of-text id
STEPS = 2500


def word_indices(texts: pa.Array) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """Distinct lower-case words, the index of every word, and n + 1 offsets of the texts' words."""
    lists = pc.ascii_split_whitespace(pc.ascii_lower(texts))
    words = lists.flatten()
    there = pc.not_equal(words, "")
    doc = np.repeat(np.arange(len(texts)), np.diff(lists.offsets.to_numpy()))[there.to_numpy(zero_copy_only=False)]
    coded = words.filter(there).dictionary_encode()
    return coded.dictionary, coded.indices.to_numpy().astype(np.int32), np.searchsorted(doc, np.arange(len(texts) + 1))


def subwords_of(words: pa.Array, path: str) -> tuple[np.ndarray, np.ndarray]:
    """Subword ids of each word with a space before it, end to end, and n + 1 offsets."""
    if not len(words):
        return np.zeros(0, np.int32), np.zeros(1, np.int64)
    spaced = pc.binary_join_element_wise(pa.scalar("", pa.large_string()), words.cast(pa.large_string()), pa.scalar(" ", pa.large_string())).cast(pa.large_string())
    return encoder(path).encode(spaced)


def gather(values: np.ndarray, offsets: np.ndarray, index: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ragged rows `index` of (values, offsets) end to end, and their sizes."""
    size = np.diff(offsets)[index]
    upto = np.cumsum(size)
    return values[np.repeat(offsets[index] - (upto - size), size) + np.arange(upto[-1] if len(upto) else 0)], size


def code_texts(index: np.ndarray, ends: np.ndarray, values: np.ndarray, offsets: np.ndarray, end: int) -> tuple[np.ndarray, np.ndarray]:
    """Subword values of texts end to end, each closed by `end`, and n + 1 offsets."""
    flat, size = gather(values, offsets, index)
    upto = np.r_[0, np.cumsum(size)][ends]
    out = np.empty(len(flat) + len(ends) - 1, values.dtype)
    close = upto[1:] + np.arange(len(ends) - 1)
    is_close = np.zeros(len(out), bool)
    is_close[close] = True
    out[is_close] = end
    out[~is_close] = flat
    return out, np.r_[0, close + 1]


class Fitted:
    """The network with its choice of codes: ids are the corpus counts of every id."""

    def __init__(self, ids: np.ndarray, path: str):
        self.path, self.size = path, encoder(path).size
        self.code = np.full(self.size, lm.RARE, np.int32)
        self.code[np.argsort(-ids, kind="stable")[: lm.HEAD]] = np.arange(lm.HEAD)
        rare = self.code == lm.RARE
        own = np.where(rare, ids + 0.5, 1.0)
        self.log_rare = np.where(rare, np.log10(own / own[rare].sum()), 0.0)

    def start(self, texts: list[str], bigrams: np.ndarray, steps: int = STEPS) -> None:
        """First fit, to a sample of texts beside the corpus counts of code pairs."""
        words, index, ends = word_indices(pa.array(texts, pa.large_string()))
        ids, offsets = subwords_of(words, self.path)
        flat, ends = code_texts(index, ends, self.code[ids], offsets, self.code[END])
        self.net = lm.train(flat, ends, steps if len(texts) > 2 else 0, whole=bigrams.reshape(lm.CODES, lm.HEAD + 1))

    def training_codes(self, row: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
        """Codes of a chunk's training texts end to end, and n + 1 offsets."""
        ends, index, ids, offsets = opened(row, self.size)
        keep, n = row.column("train").flatten().to_numpy(zero_copy_only=False).astype(bool), np.diff(ends)
        return code_texts(index[np.repeat(keep, n)], np.r_[0, np.cumsum(n[keep])], self.code[ids], offsets, self.code[END])


def packed_ints(x: np.ndarray) -> bytes:
    """int32 numbers as compressed planes of bytes: word numbers start with the common ones, so high planes are mostly zero."""
    return pa.compress(x.astype("<i4").view(np.uint8).reshape(-1, 4).T.tobytes(), "zstd", asbytes=True)


def unpacked_ints(raw: bytes, n: int) -> np.ndarray:
    planes = np.frombuffer(pa.decompress(raw, 4 * n, "zstd", asbytes=True), np.uint8) if n else np.zeros(0, np.uint8)
    return np.ascontiguousarray(planes.reshape(4, n).T).view("<i4").ravel()


def opened(row: pa.RecordBatch, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of a chunk: its texts' offsets, the index of every word, subword ids of the words and their offsets."""
    ends, sizes = row.column("ends").flatten().to_numpy(), np.frombuffer(row.column("sizes")[0].as_py(), np.int32)
    index = unpacked_ints(row.column("codes")[0].as_py(), int(ends[-1]))
    ids = np.frombuffer(row.column("subwords")[0].as_py(), np.uint16 if size <= 1 << 16 else np.uint32)
    return ends, index, ids, np.r_[0, np.cumsum(sizes)]


def gathered(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[pa.RecordBatch]:
    """Batches put together up to about `most` bytes, so that chunks are full."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if held and sum(b.nbytes for b in held) + batch.nbytes > most:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held = []
        if batch.num_rows:
            held.append(batch)
    if held:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


CHUNK_SCHEMA = "chunk long, doc_ids array<long>, train array<boolean>, words array<string>, counts array<long>, codes binary, ends array<long>, subwords binary, sizes binary, id_at array<int>, id_n array<long>"


def _chunks(path: str, size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, task = 0, TaskContext.get().partitionId()
        encoder(path).most_known = 200_000  # words of a chunk differ: keep more of them
        for batch, texts in text_chunks(gathered(batches, CHUNK), most=CHUNK):
            train = batch.column("train").to_numpy(zero_copy_only=False)
            words, index, ends = word_indices(texts)
            n = np.diff(ends)
            counts = np.bincount(index[np.repeat(train, n)], minlength=len(words))
            ids, offsets = subwords_of(words, path)
            per_id = np.bincount(ids, np.repeat(counts, np.diff(offsets)), size).astype(np.int64)
            per_id[END] += train.sum()
            ia = np.flatnonzero(per_id)
            kind = np.uint16 if size <= 1 << 16 else np.uint32
            sizes = np.diff(offsets).astype(np.int32)
            one = [[(task << 20) + at], [batch.column("doc_id").to_pylist()], [train.tolist()], [words], [counts], [packed_ints(index)], [ends], [ids.astype(kind).tobytes()], [sizes.tobytes()], [ia.astype(np.int32)], [per_id[ia]]]
            kinds = [pa.int64(), pa.list_(pa.int64()), pa.list_(pa.bool_()), pa.list_(pa.string()), pa.list_(pa.int64()), pa.binary(), pa.list_(pa.int64()), pa.binary(), pa.binary(), pa.list_(pa.int32()), pa.list_(pa.int64())]
            cols = [pa.ListArray.from_arrays(pa.array([0, len(words)], pa.int32()), words.cast(pa.string())) if i == 3 else pa.array(v, k) for i, (v, k) in enumerate(zip(one, kinds))]
            yield pa.record_batch(cols, names=[c.split()[0] for c in CHUNK_SCHEMA.split(", ")])
            at += 1

    return run


PAIR_SCHEMA = "pair_at int, pair_n long"


def _pairs(fitted: Fitted):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(lm.CODES * (lm.HEAD + 1), np.int64)
        for batch in batches:
            for i in range(batch.num_rows):
                total += lm.bigram_counts(*fitted.training_codes(batch.slice(i, 1)))
                give_back()
        at = np.flatnonzero(total)
        yield pa.record_batch([pa.array(at.astype(np.int32)), pa.array(total[at])], names=["pair_at", "pair_n"])

    return run


#: Learned parameters are summed in so many slots before the driver gets them.
SLOTS = 16
MODEL_SCHEMA = "slot int, seen double, params binary"


def _learn(fitted: Fitted):
    """One row a task: the windows it saw and, times their number, the parameters it reached."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_small()
        task = TaskContext.get().partitionId()
        learner = lm.Learner(fitted.net, seed=task)
        for batch in batches:
            for i in range(batch.num_rows):
                codes, ends = fitted.training_codes(batch.slice(i, 1))
                if len(codes):
                    learner.learn(codes, ends)
                give_back()
        if learner.seen:
            yield _model_row(task % SLOTS, learner.seen, learner.seen * learner.packed().astype(np.float64))

    return run


def _model_row(slot: int, seen: float, params: np.ndarray) -> pa.RecordBatch:
    return pa.record_batch([pa.array([slot], pa.int32()), pa.array([float(seen)]), pa.array([params.tobytes()], pa.binary())], names=["slot", "seen", "params"])


def _summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    seen, params = 0.0, None
    for batch in batches:
        for s, p in zip(batch.column("seen").to_pylist(), batch.column("params").to_pylist()):
            p = np.frombuffer(p, np.float64)
            seen, params = seen + s, p.copy() if params is None else params + p
    if params is not None:
        yield _model_row(0, seen, params)


def learn(fitted: Fitted, chunks: DataFrame) -> int:
    """Train over all training texts of the chunks; gives the number of windows seen."""
    rows = chunks.select("train", "codes", "ends", "subwords", "sizes").mapInArrow(_learn(fitted), MODEL_SCHEMA)
    rows = rows.repartition(SLOTS, "slot").mapInArrow(_summed, MODEL_SCHEMA).collect()  # at most SLOTS rows
    seen = sum(r["seen"] for r in rows)
    if seen:
        fitted.net.p = lm.unpack(sum(np.frombuffer(r["params"], np.float64) for r in rows) / seen, fitted.net.p)
    fitted.net.left_out = None
    return int(seen)


#: log_counts: sum of log10(c + 0.5) over a text's tokens; new: on a chunk's first text, its words listed in no earlier chunk.
SCORE_SCHEMA = "doc_id long, held_out boolean, n_tokens long, n_known long, log_counts double, score double, new long"


def _scores(fitted: Fitted, ends_seen: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_small()
        for batch in batches:
            for i in range(batch.num_rows):
                row = batch.slice(i, 1)
                get = lambda c: row.column(c).flatten().to_numpy(zero_copy_only=False)  # noqa: B023, E731
                ends, index, ids, offsets = opened(row, fitted.size)
                known = row.column("known").flatten()
                count = np.zeros(len(offsets) - 1, np.int64)
                count[known.field("at").to_numpy()] = known.field("n").to_numpy()
                n = np.diff(ends)
                upto = lambda x: np.r_[0, np.cumsum(x)][ends]  # noqa: B023, E731
                log_counts = np.diff(upto(np.log10(count + 0.5)[index])) + np.log10(ends_seen + 0.5)
                new = np.zeros(len(n), np.int64)
                new[0] = row.column("new")[0].as_py()
                n_known = np.diff(upto((count > 0)[index])) + (ends_seen > 0)
                flat, close = code_texts(index, ends, fitted.code[ids], offsets, fitted.code[END])
                rare = np.diff(np.r_[0, np.cumsum(fitted.log_rare[ids])][offsets])
                score = fitted.net.log10_shares(flat, close) + np.diff(upto(rare[index])) + fitted.log_rare[END]
                held = ~get("train").astype(bool)
                give_back()
                yield pa.record_batch([row.column("doc_ids").flatten(), pa.array(held), pa.array(n + 1), pa.array(n_known.astype(np.int64)), pa.array(log_counts), pa.array(score), pa.array(new)], names=[c.split()[0] for c in SCORE_SCHEMA.split(", ")])

    return run


def training_texts(docs: DataFrame, sample: int = SAMPLE, longest: int = LONGEST) -> list[str]:
    """Texts to start from: of the first `sample` training ids by hash, none longer than `longest`, a bounded number of bytes."""
    ids = docs.where("train and doc_id is not null").select("doc_id").distinct().orderBy(F.xxhash64("doc_id", F.lit(4))).limit(sample).collect()
    small = docs.sparkSession.createDataFrame([(r[0],) for r in ids], "_id long")
    rows = docs.where((F.length("text") <= longest) & F.col("train")).join(F.broadcast(small), F.col("doc_id") == F.col("_id")).select("doc_id", "text").collect()
    return [t for _, t in sorted((r[0], r[1]) for r in rows)][: 2 * sample]


COUNTS = "array<struct<at:int,n:long>>"
#: Up to so many chunks, a word's entries (one a chunk) meet in one window; beyond, they are added up before they
#: move and joined back, which adaptive execution splits.
WINDOW_CHUNKS = 4096


def corpus_counts(chunks: DataFrame, window_chunks: int = WINDOW_CHUNKS) -> DataFrame:
    """(chunk, known, new): the corpus count of each of a chunk's distinct words by its number there, and how
    many trained words are listed in no earlier chunk."""
    listed = chunks.select("chunk", F.posexplode("words").alias("at", "word"), "counts").select("chunk", "at", "word", F.col("counts")[F.col("at")].alias("n"))
    if chunks.count() <= window_chunks:
        # one shuffle by word gives each chunk's entries their corpus counts
        summed = listed.select("chunk", "at", F.expr("sum(n) over (partition by word) as n"), F.expr("row_number() over (partition by word order by chunk) = 1 as first"))
    else:
        totals = listed.groupBy("word").agg(F.sum("n").alias("total"), F.min("chunk").alias("begun"))
        summed = listed.join(totals, "word").select("chunk", "at", F.col("total").alias("n"), (F.col("chunk") == F.col("begun")).alias("first"))
    # and one by chunk brings them back: at most one entry for each of its distinct words
    fresh = F.sum(F.when(F.col("first") & (F.col("n") > 0), 1).otherwise(0))
    return summed.groupBy("chunk").agg(F.collect_list(F.struct("at", "n")).alias("known"), fresh.alias("new"))


def lm_scores(docs: DataFrame, path: str | None = None, steps: int = STEPS) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) of docs (doc_id, text, train)."""
    bounded_batches()
    path = path or model_path()
    size = encoder(path).size
    chunks = materialise(docs.select("doc_id", "text", "train").mapInArrow(_chunks(path, size), CHUNK_SCHEMA), "lm-chunks")
    per_id, per_pair = np.zeros(size, np.int64), np.zeros(lm.CODES * (lm.HEAD + 1), np.int64)
    for i, n in chunks.select(F.inline(F.arrays_zip("id_at", "id_n"))).groupBy("id_at").agg(F.sum("id_n")).collect():  # at most the tokenizer's size
        per_id[i] = n
    fitted = Fitted(per_id, path)
    pairs = chunks.select("train", "codes", "ends", "subwords", "sizes").mapInArrow(_pairs(fitted), PAIR_SCHEMA)
    pairs = pairs.groupBy("pair_at").agg(F.sum("pair_n")).toArrow()  # at most CODES ** 2
    per_pair[pairs.column(0).to_numpy()] = pairs.column(1).to_numpy()
    fitted.start(training_texts(docs), per_pair, steps)
    learn(fitted, chunks)
    give_back()
    total = chunks.select(F.expr("aggregate(counts, 0L, (a, x) -> a + x)").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    docs_seen = chunks.agg(F.coalesce(F.sum(F.size(F.filter("train", lambda x: x))), F.lit(0))).first()[0]
    # counts go from their grouping by chunk straight into the join; what needs the number of kinds comes after it
    both = chunks.select("chunk", "doc_ids", "train", "codes", "ends", "subwords", "sizes").join(corpus_counts(chunks), "chunk", "left")
    ready = both.select("doc_ids", "train", "codes", "ends", "subwords", "sizes", F.coalesce("known", F.array().cast(COUNTS)).alias("known"), F.coalesce("new", F.lit(0)).cast("long").alias("new"))
    scored = materialise(ready.mapInArrow(_scores(fitted, docs_seen), SCORE_SCHEMA), "lm-scores")
    total, kinds = int(total + docs_seen), scored.agg(F.coalesce(F.sum("new"), F.lit(0))).first()[0] + (docs_seen > 0)
    base = F.col("log_counts") - F.col("n_tokens") * F.lit(float(np.log10(total + 0.5 * (kinds + 1))))
    return scored.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(total).cast("long").alias("train_tokens"), base.alias("base_score"), "score")


def op2_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", F.coalesce(fold() != 1, F.lit(True)).alias("train"))
    return lm_scores(docs)


QUERIES = {"op2_lm_scoring": op2_lm_scoring}
ORACLES = {}
