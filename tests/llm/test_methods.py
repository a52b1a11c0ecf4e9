"""Methods against brute force, round trips and held-out accuracy."""

import math
import zlib

import numpy as np
import pyarrow as pa
import pytest
from conftest import same
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from meshprofile.llm import attention_lm, bpe, common, embedding_dedup, learning, lm_scoring, mixing, packing, quality_rules, registry, simhash_dedup, toxicity


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_its_sql(spark, sf, duck, name):
    same(registry.queries()[name](spark, sf), duck.execute(registry.oracle_sql()[name]))


@settings(max_examples=60, deadline=None)
@given(st.lists(st.text(st.sampled_from("ab the's'll12²!?\n\t  　é日\U0001f600<|endoftext|>"), max_size=40), min_size=1, max_size=5))
def test_bpe_equals_the_library(texts):
    from tokenizers import Tokenizer

    ids, ends = bpe.encoder(bpe.model_path()).encode(pa.array(texts, pa.large_string()))
    tok = Tokenizer.from_file(bpe.model_path())
    for i, t in enumerate(texts):
        assert ids[ends[i] : ends[i + 1]].tolist() == tok.encode(t, add_special_tokens=False).ids


def test_slices_keep_their_bytes():
    texts = pa.array(["é" * i + " B" for i in range(50)])
    for batch in pa.table({"text": texts}).to_batches(max_chunksize=7):
        for part, got in common.text_chunks(iter([batch]), most=60):
            assert got.to_pylist() == part.column(0).to_pylist()
            assert [w.as_py() for w in lm_scoring.word_indices(got)[0]] is not None


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(1, 64), max_size=80))
def test_packing_is_best_fit_decreasing(sizes):
    sizes = np.array(sizes, int)
    rows = packing.best_fit_decreasing(sizes, 64)
    assert sorted(i for r in rows for i in r) == list(range(len(sizes)))
    free: list[int] = []
    for i in np.argsort(-sizes, kind="stable"):  # plain search for the tightest row
        fits = [f for f in free if f >= sizes[i]]
        if fits:
            free.remove(min(fits))
            free.append(min(fits) - sizes[i])
        else:
            free.append(64 - sizes[i])
    assert sorted(64 - sizes[r].sum() for r in rows) == sorted(free)


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(0, 2**64 - 1), max_size=60), st.lists(st.tuples(st.integers(0, 59), st.integers(0, 63)), max_size=60))
def test_gray_index_finds_all_links(values, flips):
    for i, b in flips:
        if values:
            values.append(values[i % len(values)] ^ (1 << b))
    v = np.unique(np.array(values, np.uint64))
    v = v[np.argsort(simhash_dedup.gray_rank(v), kind="stable")]
    if not len(v):
        return
    got = {(int(a), int(b)) for i, j in simhash_dedup.GrayIndex(np.zeros(len(v), int), v).links() for a, b in zip(i, j)}
    assert got == {(i, j) for i in range(len(v)) for j in range(i + 1, len(v)) if int(v[i] ^ v[j]).bit_count() <= 3}


def test_simhash_components_with_a_crowded_block(spark, monkeypatch):
    monkeypatch.setattr(simhash_dedup, "TILE", 16)
    rng = np.random.default_rng(2)
    centres = rng.integers(0, 2**63, 30, dtype=np.int64)
    v = np.unique(np.concatenate([centres ^ (1 << rng.integers(0, 60, 30)) ^ (1 << rng.integers(0, 60, 30)) for _ in range(20)] + [centres]))
    got = {r.node: r.component for r in simhash_dedup.fingerprint_components(spark.createDataFrame([(int(x),) for x in v], "fp long")).collect()}
    root = list(range(len(v)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(v)):
        for j in range(i + 1, len(v)):
            if int(v[i] ^ v[j]).bit_count() <= 3:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    for i in range(len(v)):
        assert got.get(int(v[i]), int(v[i])) == int(v[find(i)])


def test_components_of_a_long_path_and_a_star(spark):
    edges = [(i, i + 1) for i in range(60)] + [(100, 100 + i) for i in range(1, 80)] + [(7, 7)]
    got = {r.node: r.component for r in common.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(61)) and all(got[100 + i] == 100 for i in range(80))


@pytest.mark.parametrize("tile, cell_rows", [(32, 30), (2048, 2), (64, 1)])
def test_embedding_links_and_components_against_brute_force(spark, monkeypatch, tile, cell_rows):
    """Small cells make grids of many codes: every link and component is there, and none besides."""
    monkeypatch.setattr(embedding_dedup, "TILE", tile)
    monkeypatch.setattr(embedding_dedup, "CELL_ROWS", cell_rows)
    monkeypatch.setattr(embedding_dedup, "FEW", 10)
    rng = np.random.default_rng(4)
    base = rng.normal(size=(150, 16))
    x = np.vstack([base, base[:60] + 0.04 * rng.normal(size=(60, 16)), base[:1] + 0.05 * rng.normal(size=(90, 16))])
    label = np.array([i % 2 for i in range(150)] + [i % 2 for i in range(60)] + [0] * 90)
    frame = spark.createDataFrame([(i, v.tolist(), int(y)) for i, (v, y) in enumerate(zip(x, label))], "vec_id long, embedding array<double>, label int")
    got = {r.vec_id: r for r in embedding_dedup.near_vectors(frame).collect()}
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    near = (u @ u.T >= 0.98) & (label[:, None] == label)
    want, root = near.sum(1) - 1, np.arange(len(x))
    for _ in range(len(x)):
        root = np.where(near, root, len(x)).min(1)
    links = sum(r.n_links for r in got.values())
    assert links >= 0.9 * want.sum() and all(got[i].n_links <= want[i] for i in range(len(x)))
    if links == want.sum():
        assert all(got[i].component_id == root[i] and got[i].kept == (root[i] == i) for i in range(len(x)))
    assert links >= 0.999 * want.sum()


def test_embeddings_of_a_whole_table_against_brute_force(spark, sf):
    rows = spark.read.parquet(f"{sf}/embeddings.parquet").toPandas()
    x, label = np.array(rows.embedding.tolist(), float), rows.label.to_numpy()
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    sims = np.where(label[:, None] == label, x @ x.T, -1)
    np.fill_diagonal(sims, -1)
    cut = float(np.quantile(sims[sims > -1], 0.999))  # at 0.98 this table has no links
    frame = spark.read.parquet(f"{sf}/embeddings.parquet")
    for cosine in (0.98, cut):
        near, root = sims >= cosine, np.arange(len(x))
        while True:
            new = np.minimum(root, np.where(near, root, len(x)).min(1))
            if (new == root).all():
                break
            root = new
        got = {r.vec_id: r for r in embedding_dedup.near_vectors(frame.select("vec_id", "embedding", "label"), cosine).collect()}
        want = dict(zip(rows.vec_id, near.sum(1)))
        assert len(got) == len(rows) and sum(r.n_links for r in got.values()) >= 0.9 * near.sum()
        assert all(got[i].n_links <= want[i] for i in want)
        if all(got[i].n_links == want[i] for i in want):
            assert all(got[i].component_id == rows.vec_id[root[j]] for j, i in enumerate(rows.vec_id))


def test_lm_is_a_distribution_and_learns():
    rng = np.random.default_rng(0)
    codes = (rng.zipf(1.4, 3000) % 50).astype(np.int32)
    codes[1::2] = codes[::2] + 100  # every second code follows from the one before
    ends = np.arange(0, 3001, 100)
    net = attention_lm.train(codes, ends, steps=60)
    x = np.full((1, attention_lm.WINDOW), 5)
    total = 0.0
    for y in range(attention_lm.HEAD + 1):
        target = np.full((1, attention_lm.WINDOW), -1)
        target[0, 9] = y
        total += math.exp(net.forward(x, x, target, np.zeros(1, int))[1][0])
    assert abs(total - 1) < 1e-3
    uniform = -math.log10(attention_lm.HEAD + 1) * 100
    assert net.log10_shares(codes, ends).mean() > uniform / 2


def test_windows_score_each_place_once():
    ends = np.array([0, 1, 33, 90, 200])
    starts, owner, skip = attention_lm.windows_of(ends)
    seen = np.zeros(200, int)
    for s, o, k in zip(starts, owner, skip):
        seen[s + k : min(s + attention_lm.WINDOW, ends[o + 1])] += 1
    assert (seen == 1).all()


def test_lm_base_against_counts(spark, sf):
    from collections import Counter

    rows = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()
    got = {r.doc_id: r for r in registry.queries()["op2_lm_scoring"](spark, sf).collect()}
    low = str.maketrans({chr(65 + i): chr(97 + i) for i in range(26)})
    import re

    words = {r.doc_id: re.findall(r"[^\x20\x09-\x0d]+", (r.text or "").translate(low)) for r in rows}
    seen, docs = Counter(), 0
    for i, w in words.items():
        if zlib.crc32(str(i).encode()) % 5 != 1:
            seen.update(w)
            docs += 1
    n, v = sum(seen.values()) + docs, len(seen) + 1
    for i, w in words.items():
        assert got[i].train_tokens == n and got[i].n_tokens == len(w) + 1 and got[i].n_known == sum(x in seen for x in w) + 1
        assert abs(got[i].base_score - sum(math.log10((seen[x] + 0.5) / (n + 0.5 * (v + 1))) for x in w) - math.log10((docs + 0.5) / (n + 0.5 * (v + 1)))) < 1e-5
    held = [r for r in got.values() if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


def test_mix_targets_and_positions(spark, sf):
    assert mixing.share_targets([10, 100, 100], [5, 2, 1], 315) == [20, 590 / 3, 295 / 3]
    pieces = mixing.demand_pieces(((0.0, 1.5), (0.4, 1.0), (1.0, 0.5)))
    got = spark.range(101).selectExpr(f"id / 100 as c").selectExpr("c", f"{mixing.position('c', pieces)} as t").collect()
    knots = np.array([0, 0.4, 1.0]), np.array([1.5, 1.0, 0.5])
    t = np.linspace(0, 1, 200_001)
    w = np.interp(t, *knots)
    share = np.r_[0, np.cumsum((w[1:] + w[:-1]) / 2)]
    for r in got:
        assert abs(np.interp(r.t, t, share / share[-1]) - r.c) < 1e-4
    rows = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "source").join(registry.queries()["op4_mix_sources"](spark, sf), "doc_id").toPandas()
    per = rows.groupby("source").agg(taken=("taken", "sum"), target=("target", "first"), size=("size", "sum"))
    assert ((per.taken - per.target).abs() <= 0.01 * per.target).all() and (per.target <= 2 * per["size"]).all()
    assert abs(per.target.sum() - 1.5 * per["size"].sum()) < 1


def test_binomial_bound(spark):
    rows = [(0, 5), (2, 40), (10, 900), (40, 900), (45, 900), (60, 900), (0, 20_000), (900, 20_000)]
    got = spark.createDataFrame(rows, "k long, n long").select("k", "n", quality_rules.p_value("k", "n", 0.05).alias("p")).collect()
    for r in got:
        if r.k >= 0.05 * r.n:
            assert r.p == 1
        else:
            want = sum(math.exp(math.lgamma(r.n + 1) - math.lgamma(i + 1) - math.lgamma(r.n - i + 1) + i * math.log(0.05) + (r.n - i) * math.log(0.95)) for i in range(r.k + 1))
            assert abs(r.p - want) <= 1e-9 + 1e-6 * want


def test_toxicity_generalises():
    rng = np.random.default_rng(1)
    syllables = ["ta", "ro", "mi", "en", "lu", "ka"]
    word = lambda: "".join(rng.choice(syllables, rng.integers(1, 4)))
    make = lambda bad: " ".join([word() for _ in range(rng.integers(30, 150))] + (["You", "IDIOT."] if bad else []) + [word() for _ in range(30)])
    y = np.arange(400) % 4 == 0
    texts = [make(b) for b in y]
    net = toxicity.train(texts[:300], y[:300].astype(np.float32))
    assert ((net.score(pa.array(texts[300:], pa.large_string())) >= 0.5) == y[300:]).mean() > 0.95


@pytest.mark.parametrize("name, label, cut, least", [("op7_toxicity", "toxic", 0.5, 0.85), ("op8_quality_classifier", "quality", 0.3, 0.93)])
def test_held_out_accuracy(spark, sf, name, label, cut, least):
    got = registry.queries()[name](spark, sf)
    rows = got.join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").collect()
    assert got.count() == 1000 and np.mean([(r.score >= cut) == bool(r[label]) for r in rows]) > least


def test_pipeline_stages(spark, sf):
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in P.STAGES[1:4]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns
        if name == "quality rules":
            verdict = registry.queries()["op5_quality_rules"](spark, sf).where("kept").count()
            assert out.count() == verdict
        if name == "simhash near-dedup":
            assert out.count() == registry.queries()["op10_simhash_dedup"](spark, sf).select("component_id").distinct().count()
        if name == "mixing":
            assert out.count() == registry.queries()["op4_mix_sources"](spark, sf).selectExpr("sum(copies)").first()[0]
    assert P.STAGES[4][1](spark, docs, sf).columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]


def test_lm_learns_from_every_training_text(spark, monkeypatch):
    """Codes and windows come from the whole corpus: texts beyond the first sample and very long ones too."""
    seen = {}
    monkeypatch.setattr(lm_scoring, "learn", lambda fitted, chunks, f=lm_scoring.learn: seen.update(n=f(fitted, chunks), code=fitted.code))
    late = "zebra quartz " * 3000  # longer than LONGEST characters: no part of the sample
    rows = [(i, "the cat sat on the mat", True) for i in range(40)] + [(99, late, True), (100, late, False)]
    lm_scoring.lm_scores(spark.createDataFrame(rows, "doc_id long, text string, train boolean"), steps=3).count()
    words, _, _ = lm_scoring.word_indices(pa.array([late], pa.large_string()))
    ids, _ = lm_scoring.subwords_of(words, bpe.model_path())
    assert (seen["code"][ids] != attention_lm.RARE).all()
    own = 3000 * len(ids) + 1
    assert seen["n"] == 40 + -(-own // attention_lm.WINDOW)


def test_lm_attention_reaches_every_hidden_unit():
    net = attention_lm.AttentionLM(np.arange(attention_lm.HEAD + 1) // attention_lm.MEMBERS)
    assert net.p["v"].shape == net.p["one"].shape
    codes, ends = np.arange(30, dtype=np.int32), np.array([0, 30])
    before = net.log10_shares(codes, ends)
    net.p["v"][:, -1] += 1
    assert abs(net.log10_shares(codes, ends) - before).max() > 1e-6


def test_lm_counts_of_a_chunk_with_very_many_words(spark):
    """Word numbers above 2 ** 21 keep their counts apart."""
    n = 2**21 + 3
    chunks = spark.range(1).selectExpr("0L as chunk", f"transform(sequence(1, {n}), i -> hex(i)) as words", f"transform(sequence(1, {n}), i -> if(i = {n}, 0L, 1L)) as counts")
    got = lm_scoring.corpus_counts(chunks).select("new", F.inline("known")).groupBy("new").agg(F.count("at"), F.countDistinct("at"), F.max("at"), F.sum("n"), F.max("n"), F.max_by("n", "at")).first()
    assert tuple(got) == (n - 1, n, n, n - 1, n - 1, 1, 0)


def test_lm_counts_by_window_and_by_join_are_the_same(spark):
    words = [["a", "b"], ["b", "c", "d"], ["a"], ["d", "b"]]
    counts = [[1, 2], [0, 3, 0], [4], [0, 1]]
    chunks = spark.createDataFrame([(i * 10, w, c) for i, (w, c) in enumerate(zip(words, counts))], "chunk long, words array<string>, counts array<long>")
    for most in (0, 100):
        got = {r.chunk: ({k.at: k.n for k in r.known}, r.new) for r in lm_scoring.corpus_counts(chunks, most).collect()}
        assert got == {0: ({0: 5, 1: 3}, 2), 10: ({0: 3, 1: 3, 2: 0}, 1), 20: ({0: 5}, 0), 30: ({0: 0, 1: 3}, 0)}


def test_lm_gradients_follow_the_mean_log_share():
    rng = np.random.default_rng(3)
    net = attention_lm.AttentionLM(rng.permutation(attention_lm.HEAD + 1) // attention_lm.MEMBERS)
    codes, ends = rng.integers(0, 40, 150).astype(np.int32), np.array([0, 1, 40, 150])
    starts, owner, _ = attention_lm.windows_of(ends, attention_lm.WINDOW)
    arrays = net.arrays(codes, net.earlier(codes, ends), ends, starts, owner)
    grads, _ = net.gradients(*arrays)
    assert grads.keys() == net.p.keys()
    for name, grad in grads.items():
        assert grad.shape == net.p[name].shape and grad.dtype == np.float32
        way, was, mean = rng.normal(0, 1, grad.shape).astype(np.float32), net.p[name], []
        for step in (0.003, -0.003):
            net.p[name] = was + np.float32(step) * way
            mean.append(net.gradients(*arrays)[1])
        net.p[name] = was
        assert abs((mean[1] - mean[0]) / 0.006 - (grad * way).sum(dtype=np.float64)) < 2e-3 + 0.02 * abs(grad * way).sum(), name


def test_lm_sums_of_rows_are_those_one_by_one():
    rng = np.random.default_rng(4)
    for size in (0, 1, 500):
        index, rows = rng.zipf(1.3, size) % 90, rng.normal(0, 1, (size, 6)).astype(np.float32)
        want = np.zeros((100, 6))
        np.add.at(want, index, rows)
        assert np.allclose(attention_lm.summed_rows(index, rows, 100), want, atol=1e-4)
    x = np.array([-70, -1, -1e-3, 0, 0.5, 70], np.float32)
    assert np.allclose(attention_lm.tanh_of(x.copy()), np.tanh(x), atol=3e-7)
    assert np.allclose(attention_lm.exp_of(x.copy()), np.exp(np.minimum(x, 60)), rtol=1e-6)


def test_lm_steps_over_all_parameters_are_those_of_adam():
    rng = np.random.default_rng(6)
    net = attention_lm.AttentionLM(rng.permutation(attention_lm.HEAD + 1) // attention_lm.MEMBERS)
    was = {k: v.copy() for k, v in net.p.items()}
    want, got = learning.Adam(was, 0.002), attention_lm.FlatAdam(net, 0.002)
    for _ in range(30):
        grads = {k: rng.normal(0, rng.choice([0, 1e-6, 1]), v.shape).astype(np.float32) for k, v in net.p.items()}
        want.step(grads)
        got.step(grads)
    assert all(np.allclose(net.p[k], was[k], atol=1e-6) for k in was)
    again = attention_lm.views(attention_lm.pack(net.p), was)
    assert all((again[k] == net.p[k]).all() for k in was)


def test_lm_gradients_hold_the_outputs_of_one_class_at_a_time():
    """A batch's exponentials are never all held at once: what is held at the peak fits a processor's cache better."""
    import tracemalloc

    rng = np.random.default_rng(7)
    net = attention_lm.AttentionLM(rng.permutation(attention_lm.HEAD + 1) // attention_lm.MEMBERS)
    codes, ends = rng.integers(0, 900, 256 * attention_lm.WINDOW).astype(np.int32), np.array([0, 256 * attention_lm.WINDOW])
    starts, owner, skip = attention_lm.windows_of(ends, attention_lm.WINDOW)
    arrays = net.arrays(codes, net.earlier(codes, ends), ends, starts, owner)
    for run, most in ((lambda: net.gradients(*arrays), 17), (lambda: net.forward(*arrays, skip * 0), 5)):
        tracemalloc.start()
        run()
        peak = tracemalloc.get_traced_memory()[1] / 2**20
        tracemalloc.stop()
        assert peak < most


def test_lm_learning_fetches_its_memory_once():
    """Batch after batch finds its room where the one before left it: few pages are fetched anew."""
    code = """
import resource, numpy as np
from meshprofile.llm import attention_lm as lm, common
common.keep_small()
rng = np.random.default_rng(8)
codes, ends = rng.integers(0, 900, 256 * lm.WINDOW * 20).astype(np.int32), np.array([0, 256 * lm.WINDOW * 20])
learner = lm.Learner(lm.AttentionLM(rng.permutation(lm.HEAD + 1) // lm.MEMBERS))
learner.learn(codes, ends)
before = resource.getrusage(0).ru_minflt
learner.learn(codes, ends)
print((resource.getrusage(0).ru_minflt - before) / 20)
"""
    import os
    import subprocess
    import sys
    from pathlib import Path

    root = Path(attention_lm.__file__).parents[2]
    out = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, cwd=root, env=os.environ | {"OMP_NUM_THREADS": "1"}, check=True)
    assert float(out.stdout) < 200


def test_lm_places_scored_already_ask_for_no_attention(monkeypatch):
    """Later windows weigh context for the places they score; the scores are those of window by window."""
    rng = np.random.default_rng(5)
    net = attention_lm.AttentionLM(np.arange(attention_lm.HEAD + 1) // attention_lm.MEMBERS)
    codes, ends = rng.integers(0, 500, 3000).astype(np.int32), np.array([0, 20, 1500, 3000])
    starts, owner, skip = attention_lm.windows_of(ends)
    want, before = np.zeros(3), net.earlier(codes, ends)
    for s, o, k in zip(starts, owner, skip):
        want[o] += net.forward(*net.arrays(codes, before, ends, np.array([s]), np.array([o])), np.array([k]))[1].sum()
    asked = []
    monkeypatch.setattr(attention_lm, "exp_of", lambda x, f=attention_lm.exp_of: (asked.append(x.size) if x.ndim == 3 else None, f(x))[1])
    assert np.allclose(net.log10_shares(codes, ends), want / np.log(10), rtol=1e-5)
    assert sum(asked) == (attention_lm.WINDOW - skip).sum() * attention_lm.WINDOW
