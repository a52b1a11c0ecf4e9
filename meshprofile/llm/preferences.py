"""Preference formatting: a shared prompt and two masked completions, in SQL functions.

A pair holds a chosen and a rejected conversation (arrays of turns). Their longest common prefix of
equal turns is rendered once as the prompt; what follows in each is its completion. Masks are spans of
code points within a completion: the content and closing mark of assistant turns, which train; all
else does not. A pair with no differing turn has two empty completions.

Nulls and odd input: a null role is "unknown", a null content is empty; turns sort by number, then
role and text, so repeated rows are repeated turns; a row without a conv_id is a conversation of one turn;
conversations without turns give an empty prompt; an empty table gives an empty result; other columns are
not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from meshprofile.llm.common import table

OPEN, CLOSE, TRAINED = "<|im_start|>", "<|im_end|>\n", "assistant"


def conversations(rows: DataFrame) -> DataFrame:
    """(conv_id, turns): one array of (role, text) for each conversation, in turn order. A conversation
    is one output row, so its own turns meet in one task; no group of conversations does."""
    turn = F.struct("turn", F.coalesce("role", F.lit("unknown")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    grouped = rows.where("conv_id is not null").groupBy("conv_id").agg(F.sort_array(F.collect_list(turn)).alias("_t"))
    grouped = grouped.unionByName(rows.where("conv_id is null").select("conv_id", F.array(turn).alias("_t")))
    return grouped.select("conv_id", F.transform("_t", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("turns"))


def with_rejected(chosen: DataFrame) -> DataFrame:
    """A rejected twin for every conversation: its last assistant turn answers with its first assistant
    turn's text (empty if that is the same turn), and what came after is cut."""
    last = F.expr(f"array_max(transform(turns, (t, i) -> if(t.role = '{TRAINED}', i, -1)))")
    first = F.expr(f"array_position(transform(turns, t -> t.role), '{TRAINED}') - 1")
    twin = F.expr(
        f"if(coalesce(_last, -1) < 0, turns, concat(slice(turns, 1, _last), array(named_struct('role', '{TRAINED}', 'text', if(_first = _last, '', turns[cast(_first as int)].text)))))"
    )
    return chosen.withColumns({"_last": last, "_first": first}).select("conv_id", F.col("turns").alias("chosen"), twin.alias("rejected"))


def render(turns: str) -> Column:
    return F.expr(f"array_join(transform({turns}, t -> concat('{OPEN}', t.role, '\n', t.text, '{CLOSE}')), '')")


def spans(turns: str) -> Column:
    """(start, end) in code points of what trains in rendered turns."""
    head = f"length('{OPEN}') + length(t.role) + 1"
    return F.expr(
        f"""aggregate({turns}, named_struct('at', 0, 'out', cast(array() as array<struct<start: int, end: int>>)),
        (a, t) -> named_struct('at', a.at + {head} + length(t.text) + length('{CLOSE}'),
          'out', if(t.role = '{TRAINED}', concat(a.out, array(named_struct('start', a.at + {head}, 'end', a.at + {head} + length(t.text) + length('{CLOSE}')))), a.out)),
        a -> a.out)"""
    )


def format_preferences(pairs: DataFrame) -> DataFrame:
    """pairs plus n_prefix, prompt, chosen_text, rejected_text, chosen_mask and rejected_mask. chosen and
    rejected are arrays of (role, text) structs without nulls inside; a null array counts as empty."""
    empty = "cast(array() as array<struct<role: string, text: string>>)"
    df = pairs.drop("n_prefix", "prompt", "chosen_text", "rejected_text", "chosen_mask", "rejected_mask", "_c", "_r")
    df = df.withColumns({"chosen": F.expr(f"coalesce(chosen, {empty})"), "rejected": F.expr(f"coalesce(rejected, {empty})")})
    differ = "array_position(zip_with(slice(chosen, 1, least(size(chosen), size(rejected))), slice(rejected, 1, least(size(chosen), size(rejected))), (a, b) -> a.role = b.role and a.text = b.text), false)"
    df = df.withColumn("n_prefix", F.expr(f"cast(if({differ} > 0, {differ} - 1, least(size(chosen), size(rejected))) as int)"))
    df = df.withColumns({"_c": F.expr("slice(chosen, n_prefix + 1, size(chosen))"), "_r": F.expr("slice(rejected, n_prefix + 1, size(rejected))"), "prompt": render("slice(chosen, 1, n_prefix)")})
    return df.withColumns({"chosen_text": render("_c"), "rejected_text": render("_r"), "chosen_mask": spans("_c"), "rejected_mask": spans("_r")}).drop("_c", "_r")


def op6_preference_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = format_preferences(with_rejected(conversations(table(spark, sf_dir, "conversations"))))
    trained = lambda m: F.aggregate(m, F.lit(0), lambda a, s: a + s["end"] - s["start"]).cast("long")
    return made.select(
        "conv_id",
        F.col("n_prefix").cast("long").alias("n_prefix"),
        "prompt",
        F.col("chosen_text").alias("chosen"),
        F.col("rejected_text").alias("rejected"),
        trained("chosen_mask").alias("chosen_trained"),
        trained("rejected_mask").alias("rejected_trained"),
    )


_ORACLE = r"""
with t as (select conv_id, row_number() over (partition by conv_id order by turn nulls first, coalesce(role, 'unknown'), coalesce(text, '')) as i, coalesce(role, 'unknown') as role, coalesce(text, '') as text from conversations),
s as (select conv_id, max(i) filter (role = 'assistant') as last, min(i) filter (role = 'assistant') as first, count(*) as n from t group by conv_id),
r as (select t.conv_id, t.i, t.role, case when t.i = s.last then case when s.first = s.last then '' else f.text end else t.text end as text
  from t join s using (conv_id) left join t f on f.conv_id = t.conv_id and f.i = s.first where s.last is null or t.i <= s.last),
j as (select t.conv_id, t.i, t.role = r.role and t.text = r.text as same from t left join r using (conv_id, i)),
p as (select conv_id, coalesce(min(i) filter (same is not true) - 1, max(i)) as n_prefix from j group by conv_id),
x as (select *, '<|im_start|>' || role || chr(10) || text || '<|im_end|>' || chr(10) as shown, case when role = 'assistant' then length(text) + 11 else 0 end as trained from t),
y as (select *, '<|im_start|>' || role || chr(10) || text || '<|im_end|>' || chr(10) as shown, case when role = 'assistant' then length(text) + 11 else 0 end as trained from r)
select p.conv_id, p.n_prefix::bigint as n_prefix,
  coalesce((select string_agg(shown, '' order by i) from x where x.conv_id = p.conv_id and x.i <= p.n_prefix), '') as prompt,
  coalesce((select string_agg(shown, '' order by i) from x where x.conv_id = p.conv_id and x.i > p.n_prefix), '') as chosen,
  coalesce((select string_agg(shown, '' order by i) from y where y.conv_id = p.conv_id and y.i > p.n_prefix), '') as rejected,
  coalesce((select sum(trained) from x where x.conv_id = p.conv_id and x.i > p.n_prefix), 0)::bigint as chosen_trained,
  coalesce((select sum(trained) from y where y.conv_id = p.conv_id and y.i > p.n_prefix), 0)::bigint as rejected_trained
from p
"""

QUERIES = {"op6_preference_format": op6_preference_format}
ORACLES = {"op6_preference_format": _ORACLE}
