"""From weights to a subset: quotas under a budget, and keyed draws."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from curator.functions.joins import small
from curator.functions.keyed import SEED, draw, key32


@dataclass(frozen=True)
class Budget:
    """A target volume; one of the three is given.  A number of documents is spent in documents, the others in tokens,
    or as the plan says."""

    tokens: int | None = None
    docs: int | None = None
    fraction: float | None = None

    def unit(self, per: str = "tokens") -> str:
        """'tokens' or 'docs': what the budget is counted in, ``per`` where a fraction leaves it open."""
        if per not in ("tokens", "docs") or (self.tokens is not None and per == "docs"):
            raise ValueError(f"a budget in tokens can't be spent per {per}")
        return "docs" if self.docs is not None else "tokens" if self.tokens is not None else per

    def volume(self, supply: int) -> float:
        """What may be spent, in the budget's unit, of a supply in the same unit."""
        if self.fraction is not None:
            return self.fraction * supply
        return float(self.tokens if self.tokens is not None else self.docs)


def quotas(weights: DataFrame, budget: float, max_repeat: float = 1.0, rounds: int = 60) -> DataFrame:
    """(w, supply, ...) -> adds quota: min(supply * max_repeat, level * w), with the level that spends the budget.

    Cells that reach their cap leave; the rest share what is left in proportion, until nothing changes.  Only two
    sums come back per round, so the table may have millions of rows.
    """
    cap = F.col("supply") * F.lit(float(max_repeat))
    all_cap = weights.agg(F.coalesce(F.sum(cap), F.lit(0.0))).first()[0]
    if all_cap <= budget:
        return weights.withColumn("quota", cap.cast("double"))
    level = 0.0
    for _ in range(rounds):
        full = (cap <= F.lit(level) * F.col("w")) if level > 0 else F.lit(False)
        spent, share = weights.agg(F.coalesce(F.sum(F.when(full, cap)), F.lit(0.0)), F.coalesce(F.sum(F.when(~full, F.col("w"))), F.lit(0.0))).first()
        new = (budget - spent) / share if share > 0 else level
        if abs(new - level) <= 1e-12 * max(1.0, new):
            break
        level = new
    return weights.withColumn("quota", F.least(cap.cast("double"), F.lit(level) * F.col("w")))


def take_exact(rows: DataFrame, quota: DataFrame, seed: int = SEED, keys: tuple[str, ...] = ("k", "j"), volume: str | None = "n_tokens") -> DataFrame:
    """Rows of each cell in keyed order until the running volume (None: their number) reaches the quota; sorts each cell."""
    w = Window.partitionBy(*keys).orderBy("__h", "doc_id").rowsBetween(Window.unboundedPreceding, 0)
    q = small(quota.select(*keys, "quota"), 40)
    out = rows.withColumn("__h", key32("doc_id", seed, "take")).join(q, list(keys)).withColumn("__run", F.sum(volume or F.lit(1)).over(w))
    return out.where(F.col("__run") <= F.col("quota") + 1e-9).drop("__h", "__run", "quota")


def take_threshold(rows: DataFrame, quota: DataFrame, seed: int = SEED, keys: tuple[str, ...] = ("k", "j")) -> DataFrame:
    """Rows whose keyed draw is under quota / supply of their cell; map-only after the small join, right in expectation."""
    q = quota.select(*keys, (F.col("quota") / F.greatest(F.col("supply").cast("double"), F.lit(1e-300))).alias("__share"))
    return rows.join(q, list(keys)).where(draw("doc_id", seed, "take") < F.col("__share")).drop("__share")


def take_repeat(rows: DataFrame, quota: DataFrame, seed: int = SEED, keys: tuple[str, ...] = ("k", "j")) -> DataFrame:
    """With repeats: ``copies`` is the whole part of quota / supply plus a keyed draw of the rest."""
    q = quota.select(*keys, (F.col("quota") / F.greatest(F.col("supply").cast("double"), F.lit(1e-300))).alias("__share"))
    copies = F.floor("__share") + (draw("doc_id", seed, "take") < F.col("__share") - F.floor("__share")).cast("long")
    return rows.join(q, list(keys)).withColumn("copies", copies.cast("int")).where("copies > 0").drop("__share")


def epoch_prefix(subset: DataFrame, part: float, seed: int = SEED) -> DataFrame:
    """A share of a subset by keyed order: half an epoch is contained in the whole one."""
    return subset.where(draw("doc_id", seed, "epoch") < part)
