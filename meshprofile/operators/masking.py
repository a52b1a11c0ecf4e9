"""Decaying zero-sum masks, as expressions recomputed from a key.

A draw's key is the party's own secret, the exchange's nonce, the party, the component's group and the
round. Nobody without a party's secret can recompute its masks, and no two exchanges share a draw as long
as nonces differ. One SHA-256 serves the LANES components of a group, eight hex digits each."""

from __future__ import annotations

import hashlib
import secrets as entropy

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SIGMA, BETA, LANES = 2.0, 0.2, 8


def fresh_secrets(parties: int) -> tuple[str, ...]:
    """One secret for each party, from the system's entropy."""
    return tuple(entropy.token_hex(16) for _ in range(parties))


def fixed_secrets(parties: int, seed: str = "s") -> tuple[str, ...]:
    """Secrets that can be told to another engine. For simulations and tests only."""
    return tuple(f"{seed}{i}" for i in range(parties))


def secrets_table(spark: SparkSession, secrets: tuple[str, ...]) -> DataFrame:
    """(party, secret); in a deployment every party holds its own row alone."""
    return spark.createDataFrame(list(enumerate(secrets)), "party int, secret string")


def secret_of(secrets: tuple[str, ...], party: str = "party") -> Column:
    """The secret of the party in a column, for few parties."""
    return F.element_at(F.array(*map(F.lit, secrets)), (F.col(party) + 1).cast("int"))


def delta(secret: Column, nonce: Column, party: Column, comp: Column, t: Column, sigma: float = SIGMA, beta: float = BETA) -> Column:
    """The draw of round t: uniform, its width shrinking by beta a round; zero before the first round."""
    digest = F.sha2(F.concat_ws(":", secret, nonce, party, F.floor(comp / LANES).cast("int"), t), 256)
    u = F.conv(F.substring(digest, (F.pmod(comp, F.lit(LANES)) * 8 + 1).cast("int"), F.lit(8)), 16, 10).cast("double") / F.lit(4294967296.0)
    return F.when(t < 0, F.lit(0.0)).otherwise((u - 0.5) * sigma * F.pow(F.lit(beta), t + 1))


def theta(secret: Column, nonce: Column, party: Column, comp: Column, t: Column, sigma: float = SIGMA, beta: float = BETA) -> Column:
    """What round t adds: its draw less the last, so that all added so far is one ever smaller draw."""
    return delta(secret, nonce, party, comp, t, sigma, beta) - delta(secret, nonce, party, comp, t - 1, sigma, beta)


def theta_sql(secret: str, nonce: str, party: str, comp: str, t: str, sigma: float, beta: float) -> str:
    """theta in Spark SQL, for lambdas over parties and rounds; secret is an expression."""

    def d(at: str) -> str:
        digest = f"sha2(concat_ws(':', {secret}, '{nonce}', {party}, cast(floor({comp} / {LANES}) as int), {at}), 256)"
        return f"((cast(conv(substring({digest}, pmod({comp}, {LANES}) * 8 + 1, 8), 16, 10) as double) / 4294967296D - 0.5D) * {sigma!r}D * pow({beta!r}D, {at} + 1))"

    return f"({d(t)} - if({t} > 0, {d(f'({t} - 1)')}, 0D))"


def delta_array(secrets: tuple[str, ...], nonce: str, comps: list[int], t: int, sigma: float, beta: float) -> np.ndarray:
    """(parties, comps) draws of round t, bit-equal to the expressions."""
    if t < 0 or sigma == 0 or beta == 0:
        return np.zeros((len(secrets), len(comps)))
    c = np.asarray(comps, np.int64)
    groups, at = np.unique(c // LANES, return_inverse=True)
    raw = b"".join(hashlib.sha256(f"{s}:{nonce}:{i}:{g}:{t}".encode()).digest() for i, s in enumerate(secrets) for g in groups.tolist())
    u = np.frombuffer(raw, ">u4").reshape(len(secrets), len(groups), LANES)[:, at, c % LANES] / 4294967296.0
    return (u - 0.5) * sigma * beta ** (t + 1)


def mask_table(spark: SparkSession, secrets: tuple[str, ...], nonce: str, comps: int, rounds: int, sigma: float = SIGMA, beta: float = BETA) -> DataFrame:
    """A preset lookup table of draws: (party, comp, t, delta)."""
    grid = secrets_table(spark, secrets).withColumn("comp", F.explode(F.sequence(F.lit(0), F.lit(comps - 1)))).withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(rounds - 1))))
    return grid.select("party", "comp", "t", delta(F.col("secret"), F.lit(nonce), F.col("party"), F.col("comp"), F.col("t"), sigma, beta).alias("delta"))


def mask_from_table(state: DataFrame, draws: DataFrame, t: int) -> DataFrame:
    """state with `shared`, masked by a lookup table instead of recomputed draws."""
    now = draws.where(F.col("t") == t).select("party", "comp", F.col("delta").alias("_now"))
    before = draws.where(F.col("t") == t - 1).select("party", "comp", F.col("delta").alias("_before"))
    both = state.join(now, ["party", "comp"], "left").join(before, ["party", "comp"], "left")
    return both.withColumn("shared", F.col("x") + F.coalesce("_now", F.lit(0.0)) - F.coalesce("_before", F.lit(0.0))).drop("_now", "_before")


def mask(state: DataFrame, t: int, secrets: DataFrame | Column, nonce: str = "0", sigma: float = SIGMA, beta: float = BETA, width: Column | None = None) -> DataFrame:
    """state with `shared`: what a party says in round t. secrets is (party, secret), or a column of them for few
    parties; width scales a component's mask."""
    joined = state.join(secrets, "party") if isinstance(secrets, DataFrame) else state.withColumn("secret", secrets)
    noise = theta(F.col("secret"), F.lit(nonce), F.col("party"), F.col("comp"), F.lit(t), sigma, beta)
    return joined.withColumn("shared", F.col("x") + (noise if width is None else noise * width)).drop("secret")
