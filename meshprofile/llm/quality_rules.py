"""Quality rules with risk-controlled cutoffs, in DataFrame functions only.

Each rule rejects a document whose figure lies above a cutoff. For every stratum and rule a grid of
cutoffs is tested on labelled good documents: with k of n rejected, the exact binomial probability
P(Bin(n, risk) <= k) is the p-value of "the true rejection rate is above risk". Cutoffs of a rule are
tested in sequence, from lax to strict, up to the first that fails (k only grows on the way, so this is
the lowest one that passes), which needs no correction within the sequence; Bonferroni's correction over
strata and rules keeps all chosen cutoffs valid at once with probability 1 - delta. A rule without a
passing cutoff rejects nothing.
A stratum's risk is shared evenly by its rules, so the union of all rules stays below it.

The strata are the languages of the labelled good documents, as the data have them. A cutoff needs some
1500 of those to pass, so the cutoffs that reach the driver are few however many languages there are.

Nulls and odd input: a null text counts as empty (no words, base_failed true); a null language is the
stratum of the empty name; a null or repeated doc_id is kept as it is (labels join on
doc_id, a label repeated for one doc_id counts once, by its lowest quality); an empty table gives an
empty result; columns that clash with the measures are replaced in `apply_quality_rules` and come back
untouched from `quality_survivors`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from meshprofile.llm.common import materialise, table, words_of

SYMBOLS = "#*$%&|<>"
RISK, DELTA = 0.02, 0.05
#: Rule -> its figure (from the measures below) and cutoffs from strict to lax.
RULES = {
    "symbols_per_word": ("n_symbols / n_words", (0.01, 0.02, 0.05, 0.1, 0.2, 0.4)),
    "shouts_per_word": ("n_shouts / n_words", (0.01, 0.02, 0.05, 0.1, 0.2, 0.4)),
    "dup_lines_share": ("n_dup_lines / n_lines", (0.05, 0.1, 0.2, 0.3, 0.5, 0.8)),
    "repeat_share": ("n_repeat_words / n_words", (0.02, 0.05, 0.1, 0.15, 0.2, 0.25)),
    "word_length": ("word_chars / n_words", (8.0, 10.0, 12.0, 15.0, 20.0, 40.0)),
}
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_shouts", "n_lines")


def with_measures(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs plus MEASURES (long) and base_failed, each text read whole and once; no shuffle."""
    raw = F.coalesce(F.col(text), F.lit(""))

    def times(piece: str) -> Column:
        return (F.octet_length(raw) - F.octet_length(F.replace(raw, F.lit(piece), F.lit("")))) / len(piece)

    docs = docs.drop("_w", "_h", "_s", "_p", "_l")
    df = docs.drop(*MEASURES, "base_failed").withColumn("_w", words_of(F.col(text)))
    df = df.withColumn("_l", F.filter(F.split(raw, "\n"), lambda x: F.btrim(x, F.lit(" \t\n\x0b\x0c\r")) != ""))
    windows = F.expr("transform(sequence(1, size(_w) - 7), i -> xxhash64(slice(_w, i, 8)))")
    df = df.withColumn("_h", F.when(F.size("_w") > 8, windows))
    # only texts in which a window comes back are sorted
    df = df.withColumn("_s", F.when(F.size(F.array_distinct("_h")) < F.size("_h"), F.expr("sort_array(transform(_h, (h, i) -> struct(h, i)))")))
    df = df.withColumn(
        "_p",
        F.expr("sort_array(array_compact(transform(_s, (x, i) -> if((i > 0 and _s[greatest(i - 1, 0)].h = x.h) or (i < size(_s) - 1 and _s[least(i + 1, size(_s) - 1)].h = x.h), x.i, null))))"),
    )
    covered = F.expr("aggregate(_p, named_struct('n', 0L, 'e', 0), (a, p) -> named_struct('n', a.n + (p + 8 - greatest(p, a.e)), 'e', p + 8), a -> a.n)")
    measures = {
        "n_words": F.size("_w").cast("long"),
        "word_chars": F.char_length(F.array_join("_w", "")).cast("long"),
        "n_symbols": sum((times(c) for c in SYMBOLS), F.lit(0)).cast("long"),
        "n_dup_lines": (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long"),
        "n_repeat_words": F.coalesce(covered, F.lit(0)).cast("long"),
        "n_shouts": times("!!").cast("long"),
        "n_lines": F.size("_l").cast("long"),
    }
    # a generator of one row: later filters and sums use its columns, never their expressions again
    out = df.select(*docs.drop(*MEASURES, "base_failed").columns, F.inline(F.array(F.struct(*[c.alias(k) for k, c in measures.items()]))))
    return out.withColumn("base_failed", F.expr("n_words < 20 or 100 * n_repeat_words > 30 * n_words"))


def stratum(lang: str = "lang") -> Column:
    return F.coalesce(F.col(lang), F.lit(""))


def figure(rule: str) -> Column:
    return F.expr(f"coalesce(try_divide({RULES[rule][0].replace(' / ', ', ')}), 0D)")


def p_value(k: str, n: str, risk: float) -> Column:
    """P(Bin(n, risk) <= k), from the term at k downwards; 1 where k is not below n * risk."""
    odds = (1 - risk) / risk
    log_top = f"aggregate(sequence(0, {k}), 0D, (a, i) -> if(i = 0, a, a + ln(({n} - {k} + i) / i))) + {k} * ln({risk!r}D) + ({n} - {k}) * ln({1 - risk!r}D)"
    tail = f"aggregate(sequence(0, {k}), named_struct('s', 0D, 't', 1D), (a, j) -> named_struct('s', a.s + a.t, 't', a.t * ({k} - j) / ({n} - {k} + j + 1) * {odds!r}D), a -> a.s)"
    return F.expr(f"case when {k} >= {n} * {risk!r}D then 1D else least(1D, exp({log_top}) * {tail}) end")


def cutoff_tests(measured: DataFrame, labels: DataFrame, risk: float = RISK) -> DataFrame:
    """One row per stratum, rule and cutoff: n good documents, k of them rejected, p."""
    truth = labels.where("doc_id is not null").groupBy("doc_id").agg(F.min("quality").alias("quality")).where("quality = 1").select(F.col("doc_id").alias("_id"))
    good = measured.where("not base_failed").join(truth, F.col("doc_id") == F.col("_id"), "left_semi").withColumn("stratum", stratum())
    sums = [F.sum((figure(r) > c).cast("long")).alias(f"k{i}_{j}") for i, r in enumerate(RULES) for j, c in enumerate(RULES[r][1])]
    wide = good.groupBy("stratum").agg(F.count(F.lit(1)).alias("n"), *sums)
    long = wide.select(
        "stratum",
        "n",
        F.inline(F.array(*[F.struct(F.lit(r).alias("rule"), F.lit(float(c)).alias("cutoff"), F.col(f"k{i}_{j}").alias("k")) for i, r in enumerate(RULES) for j, c in enumerate(RULES[r][1])])),
    )
    return long.withColumn("p", p_value("k", "n", risk / len(RULES)))


def choose_cutoffs(measured: DataFrame, labels: DataFrame, risk: float = RISK, delta: float = DELTA) -> dict[tuple[str, str], float]:
    """(stratum, rule) -> cutoff. Bonferroni's correction counts one sequence of tests for each stratum and rule."""
    tests = materialise(cutoff_tests(measured, labels, risk), "quality-tests")
    families = max(1, tests.agg(F.count_distinct("stratum")).first()[0]) * len(RULES)
    best = tests.where(F.col("p") <= F.lit(delta) / families).groupBy("stratum", "rule").agg(F.min("cutoff").alias("cutoff"))
    return {(r["stratum"], r["rule"]): r["cutoff"] for r in best.collect()}


def with_verdict(measured: DataFrame, cutoffs: dict[tuple[str, str], float]) -> DataFrame:
    bad = F.lit(False)
    for (s, r), c in sorted(cutoffs.items()):
        bad = bad | ((stratum() == s) & (figure(r) > c))
    return measured.withColumn("kept", ~F.col("base_failed") & ~bad)


def apply_quality_rules(docs: DataFrame, labels: DataFrame, risk: float = RISK, delta: float = DELTA) -> DataFrame:
    """docs with MEASURES, base_failed and kept. Texts and measures are written side by side in one pass without
    a shuffle; the cutoffs come from the measure columns of that table alone."""
    measured = materialise(with_measures(docs), "quality-measured")
    return with_verdict(measured, choose_cutoffs(measured, labels, risk, delta))


def quality_survivors(docs: DataFrame, labels: DataFrame, risk: float = RISK, delta: float = DELTA) -> DataFrame:
    """Rows of docs, all columns as they came, that neither the base rules nor a cutoff rejects."""
    held = docs.select(F.struct(*docs.columns).alias("_row"), "doc_id", "text", "lang")
    measured = materialise(with_measures(held).drop("text"), "quality-measured")
    return with_verdict(measured, choose_cutoffs(measured, labels, risk, delta)).where("kept").select("_row.*")


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    measured = materialise(with_measures(table(spark, sf_dir, "documents").select("doc_id", "text", "lang")).drop("text"), "quality-measures")
    judged = with_verdict(measured, choose_cutoffs(measured, table(spark, sf_dir, "labels")))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def _oracle() -> str:
    grid = ", ".join(f"('{r}', {c!r}::double)" for r, (_, cuts) in RULES.items() for c in cuts)
    figures = ", ".join(f"coalesce(({RULES[r][0].split(' / ')[0]})::double / nullif({RULES[r][0].split(' / ')[1]}, 0), 0) as {r}" for r in RULES)
    pick = "case g.rule " + " ".join(f"when '{r}' then f.{r}" for r in RULES) + " end"
    risk = RISK / len(RULES)
    gap = " || ".join(f"chr({ord(c)})" for c in " \t\n\x0b\x0c\r")
    symbols = " + ".join(f"(length(t) - length(replace(t, '{c}', '')))" for c in SYMBOLS)
    return rf"""
with d as (select row_number() over () as rid, doc_id, lang, coalesce(text, '') as t from documents),
w as (select *, regexp_extract_all(t, '[^\x20\x09-\x0D]+') as ws, list_filter(string_split(t, chr(10)), lambda x: trim(x, {gap}) <> '') as ls from d),
win as (select rid, i, array_to_string(list_slice(ws, i, i + 7), chr(10)) as win from (select rid, ws, unnest(range(1, len(ws) - 6)) as i from w where len(ws) >= 8)),
rep as (select rid, i from (select rid, i, count(*) over (partition by rid, win) as c from win) where c > 1),
pos as (select rid, count(distinct i + o) as n_repeat from rep, range(0, 8) as r(o) group by rid),
m as (select w.rid, doc_id, lang, len(ws) as n_words, length(array_to_string(ws, '')) as word_chars, {symbols} as n_symbols, len(ls) - len(list_distinct(ls)) as n_dup_lines,
  coalesce(n_repeat, 0) as n_repeat_words, (length(t) - length(replace(t, '!!', ''))) // 2 as n_shouts, len(ls) as n_lines from w left join pos on pos.rid = w.rid),
f as (select *, n_words < 20 or 100 * n_repeat_words > 30 * n_words as base_failed, coalesce(lang, '') as stratum, {figures} from m),
good as (select f.* from f where not base_failed and doc_id in (select doc_id from labels where doc_id is not null group by doc_id having min(quality) = 1)),
grid(rule, cutoff) as (values {grid}),
tests as (select stratum, rule, cutoff, count(*) as n, sum(case when {pick.replace("f.", "good.")} > cutoff then 1 else 0 end) as k from good, grid g group by all),
p as (select *, case when k >= n * {risk!r} then 1 else (select sum(exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln({risk!r}) + (n - i) * ln(1 - {risk!r}))) from range(0, k::bigint + 1) as r(i)) end as p from tests),
best as (select stratum, rule, min(cutoff) as cutoff from p where p <= {DELTA!r}::double / ({len(RULES)} * (select count(distinct stratum) from p)) group by all),
bad as (select distinct f.rid from f join best g on g.stratum = f.stratum where {pick} > g.cutoff)
select doc_id, n_words::bigint as n_words, word_chars::bigint as word_chars, n_symbols::bigint as n_symbols, n_dup_lines::bigint as n_dup_lines, n_repeat_words::bigint as n_repeat_words,
  base_failed, not base_failed and rid not in (select rid from bad) as kept from f
"""


QUERIES = {"op5_quality_rules": op5_quality_rules}
ORACLES = {"op5_quality_rules": _oracle()}
