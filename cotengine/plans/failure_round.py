"""One round of the second stage: score, retrieve, synthesise, accept, mix."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cotengine.operators import failure as fd
from cotengine.operators.dedup import cut_lineage
from cotengine.operators.proxy import ProxyLearner, alignment_report, proxy_rows
from cotengine.operators.shift import mix
from cotengine.sources.providers import Provider, pair_synthesizer


@dataclass(frozen=True)
class RoundConfig:
    k: int = 30
    tau: float = 0.05
    per_doc: int = 2


@dataclass
class Round:
    qdist: DataFrame
    kernel: DataFrame
    mass: DataFrame
    candidates: DataFrame
    accepted: DataFrame
    hard: DataFrame
    p_syn: DataFrame
    lost: DataFrame


def failure_driven_round(weights: DataFrame, queries: DataFrame, corpus: DataFrame, synthesizer: Provider | None = None, config: RoundConfig = RoundConfig()) -> Round:
    """weights (x_id, w), queries (x_id, vec), corpus (d_id, vec) → a round's tables.

    Queries without weight are dropped before retrieval; each retrieved document is synthesised
    once, however many failures retrieve it, and the provider's output is written at once.
    """
    qdist = fd.failure_distribution(weights, "x_id")
    failed = queries.join(qdist.select("x_id"), "x_id", "left_semi")
    kernel = cut_lineage(fd.retrieval_kernel(fd.retrieve(failed, corpus, k=config.k), config.tau), "kernel")
    mass = fd.activation_mass(qdist, kernel)
    provider = synthesizer or pair_synthesizer(config.per_doc)
    made = cut_lineage(fd.accept_consistent(provider(kernel.select("d_id").distinct())), "candidates")
    accepted = made.where("accepted")
    p_syn, lost = fd.synthetic_distribution(mass, accepted)
    return Round(qdist, kernel, mass, made, accepted, fd.resolve_by_vote(made), p_syn, lost)


def ledger(r: Round) -> DataFrame:
    parts = [df.agg(F.count("*").alias("n")).select(F.lit(name).alias("step"), "n") for name, df in (("failures", r.qdist), ("retrieved", r.kernel), ("documents", r.mass), ("candidates", r.candidates), ("accepted", r.accepted), ("hard", r.hard))]
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out


# --- the loop on the proxy learner --------------------------------------------------------------


@dataclass
class ProxyWorld:
    """Target prompts (a fifth of the vectors), the knowledge corpus (the rest) and the proposal P0.

    P0 is the corpus with its classes out of proportion, so that it differs from the target as
    a curated set differs from what a model is asked.
    """

    target: DataFrame
    corpus: DataFrame
    p0: DataFrame

    @classmethod
    def of(cls, embeddings: DataFrame, rare: float = 0.1) -> ProxyWorld:
        rows = cut_lineage(proxy_rows(embeddings), "proxy-rows")
        corpus = rows.where("id % 5 <> 0")
        p0 = corpus.withColumn("w", F.when(F.col("y") < 5, 1.0).otherwise(rare))
        total = F.broadcast(p0.agg(F.sum("w").alias("t")))  # one row
        return cls(rows.where("id % 5 = 0"), corpus, p0.crossJoin(total).withColumn("w", F.col("w") / F.col("t")).drop("t"))

    def second_stage(self, learner: ProxyLearner, lam: float, config: RoundConfig = RoundConfig()) -> tuple[Round, DataFrame]:
        """Evaluate, retrieve, synthesise, mix: a round's tables, and P1 as weighted rows.

        A synthetic pair of a document is the document's vector with its own target, which is
        what a faithful synthesiser would make of it.
        """
        judged = learner.predictions(self.target)
        weights = judged.select(F.col("id").alias("x_id"), (~F.col("right")).cast("int").alias("w"))
        queries, corpus = (df.select(F.col("id").alias(k), F.col("x").alias("vec")) for df, k in ((self.target, "x_id"), (self.corpus, "d_id")))
        done = failure_driven_round(cut_lineage(weights, "weights"), queries, corpus, None, config)
        p_syn = done.p_syn.groupBy(F.col("d_id").alias("key")).agg(F.sum("p").alias("p"))
        p1 = mix(self.p0.select(F.col("id").alias("key"), F.col("w").alias("p")), p_syn, lam, "key")
        return done, cut_lineage(self.corpus.drop("w").join(p1.select(F.col("key").alias("id"), F.col("p").alias("w")), "id"), "p1")


def _learner() -> ProxyLearner:
    return ProxyLearner(dim=64, classes=10)


def two_stage_fit(embeddings: DataFrame, *, steps: tuple[int, int] = (5, 5), rate: float = 4.0, lam: float = 0.5) -> DataFrame:
    """(stage, step, loss, target_risk): the first stage fits P0; the second goes on from it under P1."""
    world, learner, out = ProxyWorld.of(embeddings), _learner(), []
    rows = world.p0
    for stage, many in enumerate(steps, 1):
        if stage == 2:
            _, rows = world.second_stage(learner, lam)
        for step in range(many):
            risk = learner.loss_and_gradient(world.target)[0]
            out.append((stage, step, round(learner.fit(rows, steps=1, rate=rate)[0], 6), round(risk, 6)))
    out.append((2, steps[1], round(learner.loss_and_gradient(rows)[0], 6), round(learner.loss_and_gradient(world.target)[0], 6)))
    return embeddings.sparkSession.createDataFrame(out, "stage int, step int, loss double, target_risk double")


def alignment(embeddings: DataFrame, *, steps: int = 5, rate: float = 4.0, lams=(0.0, 0.5, 0.9)) -> DataFrame:
    """The theorem's two comparisons after a first stage under P0, for several mixtures and step sizes."""
    world, learner = ProxyWorld.of(embeddings), _learner()
    learner.fit(world.p0, steps=steps, rate=rate)
    rows = [(lam, *r) for lam in lams for r in alignment_report(learner, world.target, world.p0, world.second_stage(learner, lam)[1])]
    return embeddings.sparkSession.createDataFrame(rows, "lam double, eta double, align0 double, align1 double, risk0 double, risk1 double, better_aligned boolean, lower_risk boolean")


def failure_loop(embeddings: DataFrame, *, rounds: int = 3, steps: int = 5, rate: float = 4.0, lam: float = 0.5) -> DataFrame:
    """(round, failures, accuracy, target_risk, accepted): evaluate, retrieve, synthesise, mix, train, and again; the last row is the outcome."""
    world, learner, out = ProxyWorld.of(embeddings), _learner(), []
    learner.fit(world.p0, steps=steps, rate=rate)
    for i in range(rounds + 1):
        seen = learner.predictions(world.target).agg(F.count("*").alias("n"), F.count_if(~F.col("right")).alias("wrong")).first()
        risk = learner.loss_and_gradient(world.target)[0]
        accepted = None
        if i < rounds and seen.wrong:
            done, p1 = world.second_stage(learner, lam)
            accepted = done.accepted.count()
            learner.fit(p1, steps=steps, rate=rate)
        out.append((i, int(seen.wrong), round(1 - seen.wrong / seen.n, 6), round(risk, 6), accepted))
    return embeddings.sparkSession.createDataFrame(out, "round int, failures long, accuracy double, target_risk double, accepted long")
