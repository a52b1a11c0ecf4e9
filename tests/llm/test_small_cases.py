"""Nulls, empty and long texts, ties, repeated rows, empty tables, clashing columns."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from meshprofile.llm import bpe, embedding_dedup, lm_scoring, mixing, packing, preferences, quality_cnn, quality_rules, simhash_dedup, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, _fp string"
LONG = "wörd " * 60_000
ROWS = [
    (1, "the cat sat on the mat and looked at the dog", "en", "a", 1, 7, "x"),
    (1, "the cat sat on the mat and looked at the dog", "en", "a", 1, 7, "x"),
    (2, None, None, None, None, None, None),
    (3, "", "xx", "b", 0, 0, ""),
    (None, "no id here", "en", "b", 1, 1, "y"),
    (4, LONG, "de", "b", len(LONG), 2, "z"),
    (5, " \t\n   <|endoftext|> 's \U0001f600", "fr", "a", 3, 3, "q"),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (1, 1, 0), (3, 0, 1), (None, 1, 1), (4, None, None)], "doc_id long, quality int, toxic int")


def test_packing(docs, none):
    rows = packing.pack_documents(docs, 64).collect()
    back = {}
    for r in rows:
        ids, spots = np.frombuffer(r.input_ids, np.int32), np.frombuffer(r.position_ids, np.int32)
        assert len(ids) == 64 and r.cu_seqlens[-1] == r.n_tokens <= 64
        for i, (doc, at) in enumerate(zip(r.doc_ids, r.offsets)):
            a, b = r.cu_seqlens[i], r.cu_seqlens[i + 1]
            assert np.array_equal(spots[a:b], np.arange(b - a))
            back.setdefault(doc, []).append((at, ids[a:b]))
    enc = bpe.encoder(bpe.model_path())
    for doc, text in ((2, ""), (3, ""), (4, LONG), (5, ROWS[6][1]), (None, "no id here")):
        got = np.concatenate([x for _, x in sorted(back[doc], key=lambda p: p[0])])
        assert got[-1] == 50256 and enc.decode(got[:-1]) == text
    assert len(back[1]) == 2
    assert packing.pack_documents(none, 64).count() == 0


def test_lm(docs, none):
    marked = docs.withColumn("train", F.lit(True))
    got = {r.doc_id: r for r in lm_scoring.lm_scores(marked, steps=3).collect()}
    assert got[2].n_tokens == got[3].n_tokens == 1 and got[4].n_tokens == 60_001
    assert all(np.isfinite(r.score) and r.score < 0 for r in got.values())
    assert lm_scoring.lm_scores(none.withColumn("train", F.lit(True)), steps=3).count() == 0


def test_bpe(docs, none):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(bpe.model_path())
    got = docs.select("text", bpe.encode_column(F.col("text")).alias("ids")).withColumn("back", bpe.decode_column(F.col("ids"))).collect()
    for r in got:
        assert r.ids == tok.encode(r.text or "", add_special_tokens=False).ids and r.back == (r.text or "")
    assert bpe.token_digests(none).count() == 0


def test_mixing(docs, none):
    got = mixing.mix(docs).collect()
    assert len(got) == len(ROWS) and all(r.taken <= 2 * r["size"] and r.taken == r.copies * r["size"] for r in got)
    assert {r["size"] for r in got if r.doc_id in (2, 3)} == {0}
    assert mixing.mixed_documents(docs).columns == docs.columns
    assert mixing.mix(none).count() == 0 and mixing.mixed_documents(none).count() == 0


def test_quality_rules(docs, none, labels):
    got = {r.doc_id: r for r in quality_rules.apply_quality_rules(docs, labels).collect()}
    assert not got[2].kept and got[2].n_words == 0 and got[4].n_repeat_words == 60_000 and got[4].base_failed
    assert quality_rules.apply_quality_rules(none, labels).count() == 0
    assert quality_rules.apply_quality_rules(docs, labels.limit(0)).count() == len(ROWS)


@pytest.mark.parametrize("module, fit", [(toxicity, "fit_toxicity"), (quality_cnn, "fit_quality")])
def test_classifiers(docs, none, labels, module, fit):
    net = getattr(module, fit)(docs, labels)
    for frame, n in ((docs, len(ROWS)), (none, 0)):
        got = [r[0] for r in frame.select(module.score_column(net)).collect()]
        assert len(got) == n and all(0 <= v <= 1 for v in got)
    assert getattr(module, fit)(none, labels) is None
    trained = module.train(["good words here", "bad idiot words"] * 10, np.array([0, 1] * 10, np.float32))
    assert np.isfinite(docs.select(module.score_column(trained)).toPandas().to_numpy()).all()


def test_preferences(spark):
    rows = [(1, 0, "user", "hi"), (1, 1, "assistant", "yes"), (1, 1, "assistant", "yes"), (2, None, None, None), (3, 0, "user", "q"), (3, 1, "assistant", "a"), (3, 2, "user", "r"), (3, 3, "assistant", "b")]
    made = preferences.format_preferences(preferences.with_rejected(preferences.conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"))))
    got = {r.conv_id: r for r in made.collect()}
    assert got[3].n_prefix == 3 and got[3].chosen_text == "<|im_start|>assistant\nb<|im_end|>\n" and "\na<|im_end|>" in got[3].rejected_text
    for r in got.values():
        assert all("assistant" not in r.chosen_text[m.start : m.end] for m in r.chosen_mask)
    assert got[3].chosen_text[got[3].chosen_mask[0].start : got[3].chosen_mask[0].end] == "b<|im_end|>\n"
    assert got[2].chosen_text == "" and got[2].n_prefix == 1
    pairs = spark.createDataFrame([(None, None), ([("user", "x")], None)], "chosen array<struct<role:string,text:string>>, rejected array<struct<role:string,text:string>>")
    assert [r.n_prefix for r in preferences.format_preferences(pairs).collect()] == [0, 0]


def test_embeddings(spark):
    v = [1.0, 0.0, 0.0, 1.0]
    rows = [(1, v, 0), (1, v, 0), (2, v, 0), (3, v, 1), (4, None, 0), (5, [0.0] * 4, 0), (6, [1.0, None, 0.0, 0.0], 0), (7, [float("nan")] * 4, 0), (None, v, 0), (8, v, None), (9, [1.0], 0), (10, [1.0, 0.0, 0.0, 1.2], 0)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    got = {r.vec_id: r for r in embedding_dedup.near_vectors(frame).collect()}
    assert len(got) == 11 and got[None].kept and got[2].component_id == got[10].component_id == 1 and got[1].n_links == 2
    assert all(got[i].n_links == 0 and got[i].kept for i in (3, 4, 5, 6, 7, 8, 9))
    assert embedding_dedup.near_vectors(frame.limit(0)).count() == 0


@pytest.mark.parametrize("few", [1, 1000])
def test_embeddings_of_several_lengths_repeated_ids_and_clashing_columns(spark, monkeypatch, few):
    """Equal vectors of a rare length link; an id with a row without a label keeps its other row's links."""
    monkeypatch.setattr(embedding_dedup, "FEW", few)
    rows = [(1, [1.0, 0.0], 0), (2, [1.0, 0.0], 0), (3, [1.0, 0.0], 1)] + [(10 + i, [0.0, 1.0, 9.0 * i], 0) for i in range(3)]
    rows += [(20, [0.0, 1.0, 5.0], None), (20, [0.0, 1.0, 5.0], 0), (21, [0.0, 1.0, 5.0], 0), (22, [5.0], 0), (23, [1.0], 0), (24, [-1.0], 0)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    for c in ("n_links", "component_id", "kept", "valid", "vector", "visits", "home", "cell", "tile", "grp", "dim"):
        frame = frame.withColumn(c, F.lit("x"))
    got = {r.vec_id: (r.n_links, r.component_id) for r in embedding_dedup.near_vectors(frame).collect()}
    want = {1: (1, 1), 2: (1, 1), 3: (0, 3), 10: (0, 10), 22: (1, 22), 23: (1, 22), 24: (0, 24)}
    assert len(got) == 11 and want.items() <= got.items()
    x = {11: [0, 1, 9.0], 12: [0, 1, 18.0], 20: [0, 1, 5.0], 21: [0, 1, 5.0]}
    for i in x:
        want = sum(j != i and np.dot(x[i], x[j]) / np.linalg.norm(x[i]) / np.linalg.norm(x[j]) >= 0.98 for j in x)
        assert got[i] == (want, 11)


def test_simhash(docs, none):
    got = simhash_dedup.simhash_groups(docs).collect()
    assert len(got) == len(ROWS) and {r.component_id for r in got if r.doc_id in (2, 3)} == {2}
    kept = simhash_dedup.simhash_survivors(docs)
    assert kept.columns == [c for c in docs.columns if c != "_fp"] or kept.columns == docs.columns
    assert sorted((r.doc_id or 0) for r in kept.collect()) == [0, 1, 2, 4, 5]
    assert simhash_dedup.simhash_groups(none).count() == 0 and simhash_dedup.simhash_survivors(none).count() == 0


def test_simhash_keeps_one_row_of_a_group_whatever_its_ids(spark):
    """Rows alike but for the source, rows of one id with other texts, and a group without ids."""
    text, other = "a b c d e f g h", "some other words that stand alone here"
    rows = [(1, text, "x"), (1, text, "y"), (1, text + "  ", "x"), (2, text, "x"), (None, other, "x"), (None, other, "x"), (7, "only me and nobody else at all", None)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, source string").withColumn("m", F.create_map(F.lit("k"), F.lit(1)))
    got = [(r.doc_id, r.text.strip()) for r in simhash_dedup.simhash_survivors(frame).collect()]
    assert sorted(got, key=str) == sorted([(1, text), (None, other), (7, rows[-1][1])], key=str)


def test_preferences_of_odd_tables(spark):
    kinds, long = "conv_id long, turn long, role string, text string", "long " * 50_000
    rows = [(None, 0, "user", "hi"), (None, 0, "assistant", "yes"), (1, 0, "user", "q"), (1, 1, "assistant", long), (1, 2, "assistant", long + "!")]
    frame = spark.createDataFrame(rows, kinds).withColumn("prompt", F.lit("clash")).withColumn("turns", F.lit(1))
    made = preferences.format_preferences(preferences.with_rejected(preferences.conversations(frame))).collect()
    assert len(made) == 3 and sum(r.conv_id is None for r in made) == 2
    one = next(r for r in made if r.conv_id == 1)
    assert one.n_prefix == 2 and one.chosen_text[one.chosen_mask[0].start : one.chosen_mask[0].end] == long + "!<|im_end|>\n"
    none = spark.createDataFrame([], kinds)
    assert preferences.format_preferences(preferences.with_rejected(preferences.conversations(none))).count() == 0


def test_quality_survivors_give_rows_back_as_they_came(docs, none, labels):
    frame = docs.withColumn("n_words", F.lit("mine")).withColumn("kept", F.lit("mine"))
    long = " ".join(f"word{i}" for i in range(40))
    good = frame.limit(1).withColumn("text", F.lit(long)).unionByName(frame)
    got = quality_rules.quality_survivors(good, labels).collect()
    assert [r.text for r in got] == [long] and got[0].n_words == got[0].kept == "mine" and got[0].asDict().keys() == dict(good.dtypes).keys()
    assert quality_rules.quality_survivors(none, labels).count() == 0


def test_samples_of_classifiers_hold_long_texts(spark):
    from meshprofile.llm.learning import labelled_sample

    start, end = "start " * 10, " end" * 10
    rows = [(i, f"short text {i}") for i in range(20)] + [(50, start + "x " * 60_000 + end), (51, None)]
    labels = spark.createDataFrame([(i, i % 2) for i, _ in rows], "doc_id long, toxic int")
    texts, y = labelled_sample(spark.createDataFrame(rows, "doc_id long, text string"), labels, "toxic", held_out=9)
    assert len(texts) == len(y) == 21
    long = max(texts, key=len)
    assert long.startswith("start") and long.endswith("end") and 39_000 < len(long) <= 40_010


@pytest.mark.parametrize("name", ["op2_lm_scoring", "op7_toxicity", "op8_quality_classifier"])
def test_queries_with_null_ids_and_clashing_columns(spark, tmp_path, name):
    from meshprofile.llm import registry

    rows = [(i, f"some words of text number {i}", i) for i in range(30)] + [(None, "no id", 1), (3, "again", 2), (40, None, 3), (41, "long " * 9000, 4)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, score long").withColumn("predicted", F.lit("x")).withColumn("train", F.lit("x"))
    frame.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, i % 2, i % 3 // 2) for i in range(30)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    got = registry.queries()[name](spark, str(tmp_path)).collect()
    assert len(got) == len(rows) and all(np.isfinite(r.score) for r in got)
    assert [r.held_out for r in got if r.doc_id is None] == [False]


def test_packed_rows_are_written_and_read(docs, tmp_path, spark):
    packed = packing.pack_documents(docs, 64)
    packing.write_packed(packed, f"{tmp_path}/packed")
    back = {r.pack_id: r for r in spark.read.parquet(f"{tmp_path}/packed").collect()}
    assert len(back) == packed.count()
    for r in packed.collect():
        assert bytes(back[r.pack_id].input_ids) == bytes(r.input_ids) and back[r.pack_id].cu_seqlens == r.cu_seqlens
    with pytest.raises(Exception, match="exist"):
        packing.write_packed(packed, f"{tmp_path}/packed")


def _tables(spark, path, rows):
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame([(r[0], 1, 0) for r in rows], "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    return str(path)


def test_pipeline_on_odd_tables(spark, tmp_path):
    import corpus_pipeline as P

    from meshprofile.llm import common

    text = " ".join(f"word{i}" for i in range(60))
    other = " ".join(f"thing{i * i}" for i in range(80))
    rows = [(1, text, "en", "a", 5), (1, text, "en", "a", 5), (2, text, "en", "b", 5), (None, other, None, None, None), (4, None, "de", "a", 0), (5, "", "de", "a", 0)]
    common.clear_shared(spark)
    got = P.run(spark, _tables(spark, tmp_path / "odd", rows))
    assert {r.doc_id for r in got.collect()} == {1, None} and got.columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
    assert common.clear_shared(spark) == 1  # all but the last stage's input was deleted on the way
    assert P.run(spark, _tables(spark, tmp_path / "none", [])).count() == 0


def test_pipeline_against_its_stages_on_a_whole_table(spark, sf):
    """run() equals the operators' own verdicts put together by hand."""
    import corpus_pipeline as P
    from tokenizers import Tokenizer

    from meshprofile.llm import registry

    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    got = P.run(spark, sf).collect()
    calm = {r.doc_id for r in registry.queries()["op7_toxicity"](spark, sf).where("predicted = 0").collect()}
    passed = {r.doc_id for r in registry.queries()["op5_quality_rules"](spark, sf).where("not base_failed").collect()}
    ids = [r.doc_id for r in got]
    assert set(ids) <= calm & passed and max(map(ids.count, set(ids))) <= 2
    groups = {r.doc_id: r.component_id for r in registry.queries()["op10_simhash_dedup"](spark, sf).collect()}
    assert len({groups[i] for i in set(ids)}) == len(set(ids))
    tok = Tokenizer.from_file(bpe.model_path())
    assert all(r.n_tokens == len(tok.encode(docs[r.doc_id] or "", add_special_tokens=False).ids) for r in got[:200])


def test_a_cluster_without_a_shared_folder_is_refused():
    from types import SimpleNamespace

    from meshprofile.llm import common

    none = SimpleNamespace(getOrElse=lambda _: None)
    context = SimpleNamespace(master="spark://host:7077", _jsc=SimpleNamespace(sc=lambda: SimpleNamespace(getCheckpointDir=lambda: none)))
    with pytest.raises(RuntimeError):
        common.shared_dir(SimpleNamespace(sparkContext=context, conf=SimpleNamespace(get=lambda *_: None)))


def test_shared_tables_can_be_cleared(spark):
    import os

    from meshprofile.llm import common

    common.clear_shared(spark)
    kept = common.materialise(spark.range(3), "kept")
    assert kept.count() == 3 and common.clear_shared(spark) == 1
    assert not any(n.startswith("kept-") for n in os.listdir(common.shared_dir(spark).removeprefix("file:")))
