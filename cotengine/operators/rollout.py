"""Grouped rollouts: dynamic sampling, advantages, objectives, measures over generations.

A rollout table has a row per (prompt, i). Group filter and advantages share one window over
the prompt, so a plan with both has one exchange; filters run before the arrays are used.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cotengine.functions.rewards import clipped_terms, policy_ratio, total


def _prompt():
    return Window.partitionBy("prompt")


def drop_overlong(r: DataFrame, most: int) -> DataFrame:
    return r.where(F.col("len") <= most)


def filter_by_group_score(r: DataFrame, low: float = 0.1, high: float = 0.95) -> DataFrame:
    mean = F.avg(F.col("correct").cast("double")).over(_prompt())
    return r.withColumn("group_mean", mean).where(F.col("group_mean").between(low, high))


def dynamic_sampling(r: DataFrame, *, most_len: int = 16_384, low: float = 0.1, high: float = 0.95, enable: tuple = ("overlong", "difficulty")) -> DataFrame:
    """Overlong responses go first, then groups that are too easy or too hard by what is left."""
    out = drop_overlong(r, most_len) if "overlong" in enable else r
    return filter_by_group_score(out, low, high) if "difficulty" in enable else out


def _normalised(reward: Column, over) -> Column:
    std = F.stddev_pop(reward).over(over)
    return F.when(std > 1e-12, (reward - F.avg(reward).over(over)) / F.when(std > 1e-12, std)).otherwise(0.0)


def group_advantage(r: DataFrame, reward: str = "reward") -> DataFrame:
    """(A - mean) / population std within the prompt; 0 in a constant group."""
    return r.withColumn("advantage", _normalised(F.col(reward), _prompt()))


def batch_advantage(r: DataFrame, batch: str, reward: str = "reward") -> DataFrame:
    """The same over a batch, whose moments are a partial aggregate joined back: no batch has to fit a task."""
    m = r.groupBy(batch).agg(F.avg(reward).alias("_m"), F.stddev_pop(reward).alias("_s"))
    out = r.join(F.broadcast(m) if m.limit(100_001).count() <= 100_000 else m, batch)
    return out.withColumn("advantage", F.when(F.col("_s") > 1e-12, (F.col(reward) - F.col("_m")) / F.when(F.col("_s") > 1e-12, F.col("_s"))).otherwise(0.0)).drop("_m", "_s")


def reinforce_pp_advantage(r: DataFrame, batch: str, *, kl: float = 0.01, reward: str = "reward") -> DataFrame:
    """Reward minus kl times the summed log-ratio to the old policy, normalised over the batch."""
    penalty = total(F.zip_with("logp_new", "logp_old", lambda n, o: n - o))
    return batch_advantage(r.withColumn("_r", F.col(reward) - F.lit(kl) * penalty), batch, "_r").drop("_r")


def surrogate(r: DataFrame, *, norm: str = "token", low: float = 0.2, high: float = 0.28) -> DataFrame:
    """Clipped objective of each prompt: per token over the whole group, or the mean of per-response means."""
    terms = r.select("prompt", total(clipped_terms(policy_ratio(F.col("logp_new"), F.col("logp_old")), F.col("advantage"), low, high)).alias("s"), F.size("logp_new").alias("n"))
    if norm == "token":
        return terms.groupBy("prompt").agg(F.try_divide(F.sum("s"), F.sum("n").cast("double")).alias("objective"))
    if norm != "response":
        raise ValueError("norm is 'token' or 'response'")
    return terms.groupBy("prompt").agg(F.avg(F.try_divide(F.col("s"), F.col("n").cast("double"))).alias("objective"))


def clip_stats(r: DataFrame, highs: list[float], low: float = 0.2) -> DataFrame:
    """Share of tokens above each upper bound, and below the lower one."""
    ratios = r.select(policy_ratio(F.col("logp_new"), F.col("logp_old")).alias("x"))
    parts = ratios.select("x", F.explode(F.array(*map(F.lit, highs))).alias("eps_high"))
    above = F.size(F.filter("x", lambda v: v > 1 + F.col("eps_high")))
    below = F.size(F.filter("x", lambda v: v < 1 - low))
    return parts.groupBy("eps_high").agg(F.try_divide(F.sum(above), F.sum(F.size("x"))).alias("clipped_high"), F.try_divide(F.sum(below), F.sum(F.size("x"))).alias("clipped_low"))


def expected_reward(r: DataFrame, reward: str = "reward") -> DataFrame:
    return r.groupBy("prompt").agg(F.avg(reward).alias("m")).agg(F.avg("m").alias("objective"))


def pass_at_1(r: DataFrame, by: list[str] = []) -> DataFrame:
    return r.groupBy(*by, "prompt").agg(F.avg(F.col("correct").cast("double")).alias("m")).groupBy(*by).agg(F.avg("m").alias("pass_at_1"), F.count("*").alias("prompts"))


def best_at_n(r: DataFrame, by: list[str] = []) -> DataFrame:
    return r.groupBy(*by, "prompt").agg(F.max(F.col("correct").cast("double")).alias("m")).groupBy(*by).agg(F.avg("m").alias("best_at_n"))


def pass_at_k(r: DataFrame, ks: list[int]) -> DataFrame:
    """Unbiased 1 - C(n - c, k) / C(n, k), as a product over the last k draws."""
    by = r.groupBy("prompt").agg(F.count("*").alias("n"), F.count_if("correct").alias("c"))
    each = by.select("n", "c", F.explode(F.array(*map(F.lit, ks))).alias("k")).where("k <= n")
    steps = F.sequence(F.lit(0), F.col("k") - 1)
    fail = F.aggregate(steps, F.lit(1.0), lambda a, i: a * F.greatest(F.lit(0.0), (F.col("n") - F.col("c") - i) / (F.col("n") - i)))
    return each.groupBy("k").agg(F.avg(1 - fail).alias("pass_at_k"))


def majority_at_n(r: DataFrame) -> DataFrame:
    from cotengine.operators.failure import majority

    gold = r.groupBy("prompt").agg(F.min("gold").alias("gold"))
    return majority(r, ["prompt"]).join(gold, "prompt").agg(F.avg((F.col("consensus") == F.col("gold")).cast("double")).alias("majority_at_n"))


def answer_entropy(r: DataFrame) -> DataFrame:
    """Entropy of each prompt's answers in nats, from counts."""
    c = r.groupBy("prompt", "answer").agg(F.count("*").alias("c"))
    share = F.col("c") / F.sum("c").over(_prompt())
    return c.withColumn("p", share).groupBy("prompt").agg(F.sum(-F.col("p") * F.log("p")).alias("entropy"))


def adaptive_entropy(steps: DataFrame, target: float, rate: float = 0.1, start: float = 0.0) -> DataFrame:
    """Coefficient after each step: up by ``rate`` where entropy lies below the target, down where above, never negative.

    ``steps``: (step, entropy), one row a training step; they are folded in order.
    """
    rows = steps.agg(F.array_sort(F.collect_list(F.struct("step", "entropy"))).alias("x"))
    move = lambda a, s: F.greatest(F.lit(0.0), a["c"] + F.when(s["entropy"] < target, rate).otherwise(-rate))
    empty = F.array().cast("array<struct<step:bigint,coefficient:double>>")
    folded = F.aggregate("x", F.struct(F.lit(float(start)).alias("c"), empty.alias("out")), lambda a, s: F.struct(move(a, s).alias("c"), F.concat(a["out"], F.array(F.struct(s["step"].cast("long").alias("step"), move(a, s).alias("coefficient")))).alias("out")))
    return rows.select(F.explode(folded["out"]).alias("r")).select("r.step", "r.coefficient")


def budget_curve(r: DataFrame, budgets: list[int]) -> DataFrame:
    """Accuracy when a response over the budget counts as a failure."""
    each = r.select("prompt", "correct", "len", F.explode(F.array(*map(F.lit, budgets))).alias("budget"))
    ok = (F.col("correct") & (F.col("len") <= F.col("budget"))).cast("double")
    return each.groupBy("budget", "prompt").agg(F.avg(ok).alias("m")).groupBy("budget").agg(F.avg("m").alias("pass_at_1"))
