"""Toxicity by a bidirectional gated recurrent network with attention pooling, trained in numpy.

Each word enters with a word vector (of a vocabulary chosen on the labelled sample) and the mean of
its character-trigram vectors, so a word outside the vocabulary still has its spelling. Every text is
covered by overlapping windows of words; forward and backward states of a window are pooled by
attention into one probability, and a text scores the highest of its windows. Input projections are
computed once for each distinct word of a chunk.

Nulls and odd input: null and empty texts have one empty window and score like any other; a null
doc_id is not held out; repeated rows score alike; without labels the scores are 0; an empty table
gives an empty result; extra columns are neither read nor changed.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from meshprofile.llm.common import bounded_batches, flat_bytes, give_back, table, text_chunks
from meshprofile.llm.learning import Adam, fold, labelled_sample, sigmoid

WINDOW, STRIDE, BATCH, SLICE = 64, 48, 512, 1 << 15
HIDDEN, WORD_DIM, CHAR_DIM, CHARS = 8, 8, 8, 4096
FREQUENT, TELLING = 1000, 1000
PUNCTUATION = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"


def spell(words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Character-trigram buckets of the words (with edges) end to end, and the start of each word's."""
    edged = pc.binary_join_element_wise(pa.scalar("^", pa.large_string()), words, pa.scalar("$$", pa.large_string()), pa.scalar("", pa.large_string()))
    raw, offsets = flat_bytes(edged.cast(pa.large_string()))
    x = raw.astype(np.int64)
    code = (x[:-2] * 7919 + x[1:-1] * 104729 + x[2:] * 1299709) % CHARS if len(x) > 2 else np.zeros(0, np.int64)
    keep = np.ones(len(code), bool)
    inner = offsets[1:-1]
    keep[np.r_[inner - 1, inner - 2]] = False  # trigrams across two words
    n = np.diff(offsets) - 2
    return code[keep], np.cumsum(n) - n


def window_table(texts: pa.Array) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """Distinct lower-case words without outer punctuation; windows of their indices (-1 beyond the end); each window's text."""
    lists = pc.ascii_split_whitespace(pc.utf8_lower(texts))
    words = pc.utf8_trim(lists.flatten(), PUNCTUATION)
    there = pc.not_equal(words, "").to_numpy(zero_copy_only=False)
    doc = np.repeat(np.arange(len(texts)), np.diff(lists.offsets.to_numpy()))[there]
    coded = words.filter(pa.array(there)).dictionary_encode()
    code = coded.indices.to_numpy() if len(coded) else np.zeros(0, np.int32)
    n = np.bincount(doc, minlength=len(texts))
    first = np.cumsum(n) - n
    count = np.maximum(1, 1 + -(-np.maximum(n - WINDOW, 0) // STRIDE))
    owner = np.repeat(np.arange(len(texts)), count)
    start = (np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)) * STRIDE
    at = start[:, None] + np.arange(WINDOW)
    inside = at < n[owner][:, None]
    spots = np.where(inside, first[owner][:, None] + at, 0)
    return coded.dictionary, np.where(inside, code[spots] if len(code) else -1, -1).astype(np.int32), owner


def own_words(words: pa.Array, windows: np.ndarray) -> tuple[pa.Array, np.ndarray]:
    """The words that some windows use, and the windows in terms of those."""
    used, local = np.unique(windows, return_inverse=True)
    return words.take(pa.array(used[used >= 0])), local.reshape(windows.shape) - (used[0] < 0)


class Network:
    def __init__(self, vocabulary: list[str], seed: int = 5):
        rng, d, h = np.random.default_rng(seed), WORD_DIM + CHAR_DIM, HIDDEN
        self.vocabulary = vocabulary
        self.p = {
            "word": rng.normal(0, 0.3, (len(vocabulary) + 1, WORD_DIM)),
            "char": rng.normal(0, 0.3, (CHARS, CHAR_DIM)),
            "w": rng.normal(0, d**-0.5, (d, 6 * h)),
            "b": np.zeros(6 * h),
            "u": rng.normal(0, h**-0.5, (2, h, 3 * h)),
            "attend": rng.normal(0, 0.5, 2 * h),
            "out": rng.normal(0, 0.5, 2 * h),
            "bias": np.full(1, -2.0),
        }
        self.p = {k: v.astype(np.float32) for k, v in self.p.items()}

    def inputs(self, words: pa.Array) -> tuple[np.ndarray, tuple]:
        """Vectors of the distinct words, and what their gradient needs."""
        index = pc.fill_null(pc.index_in(words, pa.array(self.vocabulary, words.type)), len(self.vocabulary)).to_numpy(zero_copy_only=False)
        code, start = spell(words)
        n = np.diff(np.r_[start, len(code)])[:, None]
        chars = np.add.reduceat(self.p["char"][code], start, axis=0) / n if len(words) else np.zeros((0, CHAR_DIM), np.float32)
        return np.hstack([self.p["word"][index], chars]).astype(np.float32), (index, code, start, n)

    def projected(self, x: np.ndarray) -> np.ndarray:
        """Gate inputs of each word, with a row of zeros for index -1."""
        return np.vstack([x @ self.p["w"] + self.p["b"], np.zeros((1, 6 * HIDDEN), np.float32)])

    def run(self, gates: np.ndarray, windows: np.ndarray, keep: bool = False) -> tuple[np.ndarray, tuple | None]:
        """Logit of each window; with keep, what the backward pass needs."""
        b, t = windows.shape
        h3 = 3 * HIDDEN
        x = np.empty((t, 2, b, h3), np.float32)
        rows = gates[windows.T]
        x[:, 0], x[:, 1] = rows[:, :, :h3], rows[::-1, :, h3:]
        there = np.stack([windows.T >= 0, windows.T[::-1] >= 0], 1)[..., None]
        h, states, saved = np.zeros((2, b, HIDDEN), np.float32), np.empty((t + 1, 2, b, HIDDEN), np.float32), []
        states[0] = 0
        for s in range(t):
            uh = h @ self.p["u"]
            zr = x[s, ..., : 2 * HIDDEN] + uh[..., : 2 * HIDDEN]
            np.negative(zr, out=zr)
            np.exp(np.minimum(zr, 30, out=zr), out=zr)
            zr += 1
            np.reciprocal(zr, out=zr)
            z, r, un = zr[..., :HIDDEN], zr[..., HIDDEN:], uh[..., 2 * HIDDEN :]
            n = np.tanh(x[s, ..., 2 * HIDDEN :] + r * un)
            new = n + z * (h - n)
            h = np.where(there[s], new, h)
            states[s + 1] = h
            if keep:
                saved.append((z, r, un, n))
        both = np.concatenate([states[1:, 0], states[:0:-1, 1]], axis=-1)  # time, window, 2 * hidden
        mask = (windows.T >= 0).astype(np.float32)
        e = both @ self.p["attend"]
        a = np.exp(np.where(mask > 0, e - np.where(mask > 0, e, -1e9).max(0), -1e9)) * mask
        a /= np.maximum(a.sum(0), 1e-9)
        v = both @ self.p["out"]
        logit = (a * v).sum(0) + self.p["bias"][0]
        return logit, (x, there, states, saved, both, a, v) if keep else None

    def back(self, windows: np.ndarray, kept: tuple, d: np.ndarray) -> tuple[dict[str, np.ndarray], np.ndarray]:
        """Gradients of the recurrent part and of each gate input, for d = loss / logit."""
        x, there, states, saved, both, a, v = kept
        t, _, b, _ = x.shape
        mean = (a * v).sum(0)
        de = a * (v - mean) * d
        g = {"out": np.einsum("tb,tbh->h", a * d, both), "attend": np.einsum("tb,tbh->h", de, both), "bias": np.array([d.sum()], np.float32)}
        db = (a * d)[..., None] * self.p["out"] + de[..., None] * self.p["attend"]
        dh_out = np.stack([db[..., :HIDDEN], db[::-1, :, HIDDEN:]], 1)
        dx, du, dh = np.zeros_like(x), np.zeros_like(self.p["u"]), np.zeros((2, b, HIDDEN), np.float32)
        for s in range(t - 1, -1, -1):
            z, r, un, n = saved[s]
            h = states[s]
            dh = dh + dh_out[s]
            dn = np.where(there[s], dh, 0)
            dz = dn * (h - n) * z * (1 - z)
            dpre = dn * (1 - z) * (1 - n * n)
            dr = dpre * un * r * (1 - r)
            dx[s] = np.concatenate([dz, dr, dpre], -1)
            duh = np.concatenate([dz, dr, dpre * r], -1)
            du += np.swapaxes(h, 1, 2) @ duh
            dh = duh @ np.swapaxes(self.p["u"], 1, 2) + np.where(there[s], dh * z, dh)
        g["u"] = du
        rows = np.concatenate([dx[:, 0], dx[::-1, 1]], -1)
        return g, rows

    def window_logits(self, words: pa.Array, windows: np.ndarray) -> np.ndarray:
        parts = [self.inputs(words.slice(i, SLICE))[0] @ self.p["w"] + self.p["b"] for i in range(0, len(words), SLICE)]
        gates = np.vstack([*parts, np.zeros((1, 6 * HIDDEN), np.float32)])
        return np.concatenate([self.run(gates, windows[i : i + BATCH])[0] for i in range(0, len(windows), BATCH)])

    def score(self, texts: pa.Array) -> np.ndarray:
        words, windows, owner = window_table(texts)
        best = np.full(len(texts), -np.inf)
        np.maximum.at(best, owner, self.window_logits(words, windows))
        return sigmoid(best)


def train(texts: list[str], y: np.ndarray, epochs: int = 6, batch: int = 128, steps: int = 400, rate: float = 0.02, decay: float = 0.1, seed: int = 5) -> Network | None:
    """Each epoch trains on every text's currently highest window (and one other), so a long text is labelled by its worst part."""
    if not len(texts) or y.min() == y.max():
        return None
    words, windows, owner = window_table(pa.array(texts, pa.large_string()))
    key = np.unique((owner[:, None] * (len(words) + 1) + windows)[windows >= 0])
    doc, word = key // (len(words) + 1), key % (len(words) + 1)
    df = np.bincount(word, minlength=len(words))
    pos = np.bincount(word[y[doc] > 0], minlength=len(words))
    del key, doc, word
    share = y.mean()
    telling = (pos - df * share) / np.sqrt(df * share * (1 - share) + 1)
    pick = np.unique(np.r_[np.argsort(-df, kind="stable")[:FREQUENT], np.argsort(-telling, kind="stable")[:TELLING]])
    names = words.take(pa.array(pick)).to_pylist()
    net, rng = Network(names, seed), np.random.default_rng(seed)
    adam = Adam(net.p, rate, decay)
    first = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
    n = np.diff(np.r_[first, len(owner)])
    batch = max(16, min(batch, len(texts) // 16))
    for epoch in range(max(epochs, -(-steps * batch // len(texts)))):
        logits = np.concatenate([net.window_logits(*own_words(words, windows[i : i + 2048])) for i in range(0, len(windows), 2048)]) if epoch else rng.random(len(owner))
        order = np.lexsort((-logits, owner))
        chosen = np.r_[order[first], first[y < 1] + (rng.random((y < 1).sum()) * n[y < 1]).astype(int)]
        chosen = rng.permutation(np.unique(chosen))
        for i in range(0, len(chosen), batch):
            part = windows[chosen[i : i + batch]]
            used, local = own_words(words, part)
            x, (index, code, start, size) = net.inputs(used)
            logit, kept = net.run(net.projected(x), local, keep=True)
            d = ((sigmoid(logit) - y[owner[chosen[i : i + batch]]]) / len(part)).astype(np.float32)
            g, rows = net.back(local, kept, d)
            dg = np.zeros((len(used) + 1, 6 * HIDDEN), np.float32)
            np.add.at(dg, local.T.ravel(), rows.reshape(-1, 6 * HIDDEN))
            dg = dg[:-1]
            g |= {"w": x.T @ dg, "b": dg.sum(0), "word": np.zeros_like(net.p["word"]), "char": np.zeros_like(net.p["char"])}
            dx = dg @ net.p["w"].T
            np.add.at(g["word"], index, dx[:, :WORD_DIM])
            np.add.at(g["char"], code, np.repeat(dx[:, WORD_DIM:] / size, size[:, 0], axis=0))
            adam.step({k: v.astype(np.float32) for k, v in g.items()})
    return net


def score_column(net: Network | None, text: str = "text") -> Column:
    if net is None:
        return F.lit(0.0)
    bounded_batches()

    @F.arrow_udf(DoubleType())
    def score(texts: pa.Array) -> pa.Array:
        parts = [net.score(t) for _, t in text_chunks(iter([pa.record_batch([texts], names=["text"])]))]
        return pa.array(np.concatenate(parts) if parts else np.zeros(0))

    return score(F.col(text))


def fit_toxicity(docs: DataFrame, labels: DataFrame) -> Network | None:
    net = train(*labelled_sample(docs, labels, "toxic"))
    give_back()
    return net


def drop_toxic(docs: DataFrame, labels: DataFrame, threshold: float = 0.5) -> DataFrame:
    return docs.where(score_column(fit_toxicity(docs, labels)) < threshold)


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = docs.select("doc_id", F.coalesce(fold() == 0, F.lit(False)).alias("held_out"), score_column(fit_toxicity(docs, table(spark, sf_dir, "labels"))).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


QUERIES = {"op7_toxicity": op7_toxicity}
ORACLES = {}
