"""Secret-sharing sums: every party splits each whole number into random shares for all others."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PRIME = (1 << 61) - 1


def additive_shares(values: DataFrame, parties: int, secret: str = "s", scale: int = 1_000_000) -> DataFrame:
    """(comp, total) of values (party, comp, x), x rounded to 1/scale: each value becomes `parties` shares that
    add up to it modulo a prime; receivers add what they got; only those sums are added in the open.
    All-to-all: parties * (parties - 1) messages a component."""
    fixed = values.withColumn("v", F.expr(f"cast(pmod(cast(round(x * {scale}) as decimal(38,0)), {PRIME}BD) as decimal(38,0))"))
    drawn = fixed.withColumn("to", F.explode(F.sequence(F.lit(0), F.lit(parties - 1)))).withColumn(
        "r", F.expr(f"cast(conv(substring(sha2(concat_ws(':', '{secret}', party, comp, to), 256), 1, 15), 16, 10) as decimal(38,0))")
    )
    others = drawn.where("to > 0").groupBy("party", "comp").agg(F.expr(f"cast(pmod(sum(r), {PRIME}BD) as decimal(38,0))").alias("known"))
    shares = drawn.join(others, ["party", "comp"], "left").withColumn("share", F.expr(f"if(to = 0, cast(pmod(v - coalesce(known, 0), {PRIME}BD) as decimal(38,0)), r)"))
    held = shares.groupBy("to", "comp").agg(F.expr(f"cast(pmod(sum(share), {PRIME}BD) as decimal(38,0))").alias("held"))
    total = held.groupBy("comp").agg(F.expr(f"cast(pmod(sum(held), {PRIME}BD) as decimal(38,0))").alias("t"))
    return total.select("comp", (F.expr(f"cast(if(t > {PRIME // 2}BD, t - {PRIME}BD, t) as double)") / scale).alias("total"))


def messages_needed(parties: int, comps: int) -> int:
    return parties * (parties - 1) * comps
