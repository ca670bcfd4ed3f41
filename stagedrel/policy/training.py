"""Supervised warm-up, group-relative updates, and the two-stage loop around them."""

from __future__ import annotations

import json
import time
from collections.abc import Sequence
from dataclasses import dataclass, field
from types import SimpleNamespace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Config, effective_batch
from ..functions import objective as O
from ..functions import responses, rewards
from ..functions.labels import NONE
from ..functions.portable import hash_hex
from ..functions.regions import pool
from ..ontology import LABELS, rows
from ..operators import sampling, schedule
from ..sources.io import write_stage
from ..sources.tables import build_samples
from . import expert, softmax
from .softmax import Policy, warmup_lr

PARTIAL, FEATURES = "i int, g double", "sample_id long, gold string, obj_type string, ent_type string, split string, x array<double>"


def new_policy(flat: bool = False, without: Sequence[str] = ()) -> Policy:
    """An untrained policy over the ontology's labels, or over all but some of them."""
    return Policy([(r[0], r[1], r[2]) for r in rows() if not r[4] and r[0] not in without], flat=flat)


def features(spark, sf_dir: str) -> DataFrame:
    """Computed once and written: the frozen parts of the model."""
    s = build_samples(spark, sf_dir).select("sample_id", "gold", "obj_type", "ent_type", "split", "text", F.concat(pool(F.col("image"), 8), pool(F.col("crop"), 4)).alias("pooled"))
    return write_stage(s.mapInPandas(softmax.feature_batches, FEATURES), "features")


def _sums(partials: DataFrame) -> dict[int, float]:
    """As many rows as the policy has weights (three times that for a chain), and a few."""
    return {r[0]: r[1] for r in partials.groupBy("i").agg(F.sum("g")).collect()}


def _array(got: dict[int, float], shape, at: int = 0) -> np.ndarray:
    n = int(np.prod(shape))
    return np.array([got.get(at * n + i, 0.0) for i in range(n)]).reshape(shape)


def train_sft(feats: DataFrame, policy: Policy, epochs: int = 20, lr: float = 0.05, warmup: float = 0.05, trainable: Sequence[str] | None = None, batch: int = 128, seed: int = 42, distributed: bool = False) -> tuple[Policy, list[float]]:
    """(policy, mean loss over each epoch): an update for each ``batch`` rows, in an order by hash that changes with the epoch.

    Each update needs the weights of the one before, so an epoch is a chain. By default one task carries the weights
    through the epoch's ordered rows and holds one batch of them: a job an epoch. ``distributed`` makes a job of each
    batch instead, with partial sums over the cluster, for policies whose batches are worth one; both make the same updates.
    Heads that are not ``trainable`` keep their weights.
    """
    policy, adam, losses = policy.copy(), softmax.Adam(), []
    mask = np.zeros_like(policy.theta)
    for name, span in policy.heads.items():
        mask[span] = trainable is None or name in trainable
    columns = [c for c in ("sample_id", "gold", "obj_type", "ent_type", "style", "related", "x") if c in feats.columns]
    feats, n = feats.select(*columns), feats.count()
    total = epochs * -(-n // batch)
    for e in range(epochs if n else 0):
        order = hash_hex(seed, f"sft{e}", F.col("sample_id"))
        if distributed:
            ranked = write_stage(sampling.hash_rank(feats, order, ["sample_id"]).withColumn("step", F.expr(f"rank div {batch}")), "sft-epoch", ("step",))
            loss = 0.0
            for s in range(-(-n // batch)):
                got = _sums(ranked.where(F.col("step") == s).mapInPandas(softmax.sft_partial(policy), PARTIAL))
                loss += got[-1]
                policy.theta += adam.step(_array(got, policy.theta.shape) / got[-2], warmup_lr(adam.t, total, lr, warmup)) * mask
            losses.append(loss / n)
        else:
            chain = feats.withColumn("o", order).repartition(1).sortWithinPartitions("o", "sample_id").drop("o")
            got = _sums(chain.mapInPandas(softmax.sft_chain(policy, adam, batch, mask, total, lr, warmup), PARTIAL))
            policy.theta, m, v = (_array(got, policy.theta.shape, k) for k in range(3))
            adam = softmax.Adam(m, v, int(got[-3]))
            losses.append(got[-1] / got[-2])
    return policy, losses


ROLLOUT = "sample_id long, k long, gold string, response string, lp_old double, lp_ref double, outcomes array<int>, x array<double>"


def generate(feats: DataFrame, policy: Policy, k: int = 1, temperature: float = 0.0, seed: str = "0", ref: Policy | None = None) -> DataFrame:
    """Reasoning and answer for each sample; at temperature 0 the best, else k sampled by hash."""
    return feats.select("sample_id", "gold", "x").mapInPandas(softmax.rollout_batches(policy, ref or policy, k, temperature, seed), ROLLOUT)


def predict(feats: DataFrame, policy: Policy) -> DataFrame:
    out = generate(feats, policy)
    return out.select("sample_id", "gold", responses.parse_response(F.col("response"))["answer"].alias("pred"))


def scored(rolled: DataFrame, cfg: Config) -> DataFrame:
    """Rewards of the texts and advantages in their groups."""
    labels = F.array(*[F.lit(x) for x in LABELS])
    text = responses.truncate_tokens(F.col("response"), cfg.rl.max_tokens)
    r = rolled.withColumn("response", text).withColumn("answer", responses.parse_response(F.col("response"))["answer"])
    r = r.withColumns({"r_format": rewards.format_reward(F.col("response"), labels), "r_length": rewards.length_reward(F.col("response"), cfg.rl.length_threshold), "r_answer": rewards.answer_reward(F.col("answer"), F.col("gold"))})
    r = r.withColumn("reward", rewards.total_reward(F.col("r_format"), F.col("r_length"), F.col("r_answer"), cfg.rl.reward_weights))
    return r.withColumn("adv", O.advantage_flat("reward", ["sample_id"], cfg.rl.ddof))


@dataclass
class Log:
    steps: list[dict] = field(default_factory=list)


class RunState:
    """The weights after each job of updates in a table of the run's folder, so that a run that lost its driver goes on where it was."""

    SCHEMA = "step int, epoch int, theta array<double>, log string"

    def __init__(self, spark, folder: str | None):
        self.spark, self.folder = spark, folder

    def save(self, entries: list[tuple[int, int, dict]], policy: Policy) -> None:
        """entries: (step, epoch, line of the log) of the steps since the last call; the weights stand beside the last."""
        if self.folder and entries:
            table = [(at, epoch, policy.theta.ravel().tolist() if at == entries[-1][0] else None, json.dumps(entry)) for at, epoch, entry in entries]
            self.spark.createDataFrame(table, self.SCHEMA).coalesce(1).write.mode("append").parquet(self.folder)

    def restore(self, policy: Policy, log: Log) -> int:
        """The number of steps that are done; policy and log take up what they left."""
        if not self.folder:
            return 0
        try:
            kept = self.spark.read.schema(self.SCHEMA).parquet(self.folder).dropDuplicates(["step"])
            rows = kept.select("step", "log").collect()  # a line a step
        except Exception as e:  # no step yet
            if "PATH_NOT_FOUND" not in str(e):
                raise
            return 0
        if not rows:
            return 0
        last = max(r["step"] for r in rows)
        policy.theta = np.array(kept.where(F.col("step") == last).first()["theta"]).reshape(policy.theta.shape)
        log.steps += [json.loads(r["log"]) for r in sorted(rows, key=lambda r: r["step"])]
        return last + 1


def group_relative_step(rolled: DataFrame, policy: Policy, mu: int = 2, lr: float = 0.2, eps: float = 0.2, beta: float = 0.001) -> tuple[Policy, list[float], dict]:
    """mu ascents on the same responses; the old log-probabilities stay those of the rollout. Also the means of what the responses earned."""
    policy, values, told = policy.copy(), [], {}
    columns = ["x", "outcomes", "adv", "lp_old", "lp_ref", *[c for c in softmax.STATS if c in rolled.columns]]
    for k in range(mu):
        got = _sums(rolled.select(*columns).mapInPandas(softmax.update_partial(policy, eps, beta), PARTIAL))
        n = got.get(-2, 0.0)
        if not n:
            break
        if not k:
            told = {c: got[-3 - i] / n for i, c in enumerate(columns[5:])} | {"responses": int(n)}
        values.append(got[-1] / n)
        policy.theta += lr * _array(got, policy.theta.shape) / n
    return policy, values, told


def epoch_batches(pools: DataFrame, t: int, none_share: float, cfg: Config, strategy: str) -> tuple[DataFrame, int]:
    """(sample_id, pool, step of epoch t; number of steps): mini-batches of the effective size by the epoch's quotas, from all that the epoch holds."""
    batch = effective_batch(cfg.rl)
    chosen = write_stage(schedule.epoch_pool(pools, t, none_share, cfg.rl.alpha, cfg.seed, strategy), f"epoch{t}")
    if strategy == "raw":  # no quotas: a shuffle of all
        dealt = sampling.hash_rank(chosen, hash_hex(cfg.seed, f"batch{t}", F.col("sample_id")), ["sample_id"]).withColumn("step", F.expr(f"rank div {batch}"))
    else:
        dealt = schedule.assign_batches(chosen, *schedule.batch_quota(batch, t, cfg.rl.alpha, "paper", strategy), t, cfg.seed)
    dealt = write_stage(dealt.select("sample_id", "pool", F.col("step").cast("int").alias("step")), f"batches{t}")
    return dealt, (dealt.agg(F.max("step")).first()[0] or 0) + 1 if not dealt.isEmpty() else 0


CHAIN = "step int, i int, g double"


def _chain_epoch(rows: DataFrame, policy: Policy, ref: Policy, cfg: Config, t: int, strategy: str, first: int, last: int, at: int, total: int) -> list[dict]:
    """Steps first to last - 1 of epoch t in one task: moves the policy's weights and gives the lines of the log."""
    if first >= last:
        return []

    own = rows.where(F.col("step").between(first, last - 1)).select("sample_id", "gold", "x", "step", (F.col("pool") == "easy").cast("int").alias("easy"))
    rates = [warmup_lr(at + s, total, cfg.engine.rl, cfg.rl.warmup) for s in range(last)]
    chain = own.repartition(1).sortWithinPartitions("step", "sample_id").mapInPandas(softmax.rl_chain(policy, ref, SimpleNamespace(**vars(cfg.rl)), frozenset(LABELS), rates.__getitem__, f"{cfg.seed}:{t}"), CHAIN)
    got: dict[int, dict[int, float]] = {}
    for s, i, g in chain.collect():  # the weights, and seven numbers a step
        got.setdefault(s, {})[i] = g
    if -1 in got:
        policy.theta = _array(got.pop(-1), policy.theta.shape)
    entries = []
    for s, x in sorted(got.items()):
        n, easy = int(x[0]), round(x[6])
        told = dict(zip(softmax.STATS, (x[2], x[3], x[4], x[5]), strict=False))
        entries.append({"epoch": t, "step": s, "strategy": strategy, "lr": rates[s], "easy": easy, "hard": n // cfg.rl.k - easy, "objective": x[1], **told, "responses": n})
    return entries


def train_rl(feats: DataFrame, pools: DataFrame, policy: Policy, none_share: float, cfg: Config | None = None, strategy: str = "progressive", epochs: int | None = None, mode: str = "epoch_exact", max_steps: int | None = None, run_dir: str | None = None, distributed: bool = False) -> tuple[Policy, Log]:
    """Epochs over hard rows and a shrinking draw of easy ones, against the frozen policy it starts from.

    Each step needs the weights of the one before, so an epoch is a chain. By default one task carries the weights through
    the epoch's ordered rows and holds one batch of them. ``distributed`` makes jobs of each step instead, with written
    rollouts, rewards as column functions and partial sums over the cluster, for policies whose batches are worth it; both
    make the same updates.

    ``epoch_exact`` deals the epoch's rows to mini-batches by the quotas of the epoch; ``step_draw`` draws each batch
    anew from both pools, for as many steps, and is always distributed. The learning rate warms up once, over all steps.
    ``max_steps`` ends the run early; with ``run_dir`` the weights are kept after each epoch (distributed: each step), and
    a run with the same folder goes on from there.
    """
    cfg = cfg or Config()
    spark, ref, policy, log = feats.sparkSession, policy.copy(), policy.copy(), Log()
    state = RunState(spark, run_dir)
    done = state.restore(policy, log)
    plan = [epoch_batches(pools, t, none_share, cfg, strategy) for t in range(1, (epochs or cfg.rl.epochs) + 1)]
    total, at = sum(n for _, n in plan), 0
    slim = feats.select("sample_id", "gold", "x")
    for t, (dealt, steps) in enumerate(plan, 1):
        if at + steps <= done:
            at += steps
            continue
        if mode == "epoch_exact" and not distributed:
            last = steps if max_steps is None else min(steps, max_steps - at)
            entries = _chain_epoch(slim.join(dealt, "sample_id"), policy, ref, cfg, t, strategy, max(0, done - at), last, at, total)
            state.save([(at + e["step"], t, e) for e in entries], policy)
            log.steps += entries
            at += steps
            continue
        # features of the epoch's rows beside their step: a step reads its own part of the table
        rows = write_stage(slim.join(dealt, "sample_id").repartition("step"), f"epoch-rows{t}", ("step",)) if mode == "epoch_exact" else None
        for s in range(steps):
            if at < done or (max_steps is not None and at >= max_steps):
                at += at < done
                continue
            if rows is not None:
                own = rows.where(F.col("step") == s)
            elif strategy == "raw":
                own = slim.join(dealt.where(F.col("step") == s), "sample_id")
            else:
                easy, hard = schedule.batch_quota(effective_batch(cfg.rl), t, cfg.rl.alpha, "paper", strategy)
                quotas = spark.createDataFrame([("easy", easy), ("hard", hard)], "pool string, quota long")
                own = slim.join(sampling.hash_select(pools, ["pool"], hash_hex(cfg.seed, f"step{t}.{s}", F.col("sample_id")), ["sample_id"], quotas).select("sample_id", "pool"), "sample_id")
            rolled = generate(own, policy, cfg.rl.k, cfg.rl.temperature, f"{cfg.seed}:{t}:{s}", ref)
            rolled = scored(rolled, cfg).drop("response", "answer").join(F.broadcast(own.select("sample_id", (F.col("pool") == "easy").cast("int").alias("easy"))), "sample_id")  # a batch
            rolled = write_stage(rolled, "rollout")  # once: the mu passes must see the same responses
            lr = warmup_lr(at, total, cfg.engine.rl, cfg.rl.warmup)
            policy, values, told = group_relative_step(rolled, policy, cfg.rl.mu, lr, cfg.rl.eps, cfg.rl.beta)
            n = told.get("responses", 0) // cfg.rl.k
            easy = round(told.pop("easy", 0.0) * n)
            entry = {"epoch": t, "step": s, "strategy": strategy, "lr": lr, "easy": easy, "hard": n - easy, "objective": values[0] if values else 0.0, **told}
            log.steps.append(entry)
            state.save([(at, t, entry)], policy)
            at += 1
    return policy, log


@dataclass
class Trained:
    policy: Policy
    stage1: Policy
    losses: list[float]
    pools: DataFrame | None
    log: Log | None
    seconds: dict[str, float]


def taught_by(annotated: DataFrame, labels: Sequence[str] = LABELS, threshold: int = 1024, max_tokens: int = 2096) -> DataFrame:
    """(sample_id, gold, obj_type, ent_type, style, related): what the retained responses say, step by step; gold is their answer.

    Responses are cut at ``max_tokens`` first; those that are not well formed or answer wrongly teach nothing.
    """
    x = annotated.withColumn("response", responses.truncate_tokens(F.col("response"), max_tokens))
    # a lambda's variable: the filter below names the text a hundred times, which would outgrow a compiled method
    x = x.withColumn("p", F.get(F.transform(F.array("response"), responses.parse_response), F.lit(0)))
    x = x.where(responses.reject_reason(F.col("p"), F.col("gold"), F.array(*[F.lit(v) for v in labels])) == "ok")
    step = lambda k: F.get(F.col("p")["steps"], F.lit(k - 1))
    types = r"types (\w+) and (\w+)"
    return x.select(
        "sample_id", F.col("p")["answer"].alias("gold"), F.regexp_extract(step(4), types, 1).alias("obj_type"), F.regexp_extract(step(4), types, 2).alias("ent_type"),
        F.when(F.length("response") > threshold, 0).otherwise(1).alias("style"), step(2).contains("yes").cast("int").alias("related"),
    )


def stage_one(feats: DataFrame, cfg: Config, epochs: int | None = None) -> tuple[Policy, DataFrame, DataFrame, list[float]]:
    """(policy, retained, rest, losses): a quarter of each class, annotated, filtered, learned from what the annotations say."""
    train = feats.where("split = 'train'")
    drawn, rest = sampling.stratified_draw(train, frac=cfg.sft.fraction, seed=cfg.seed)
    said = taught_by(expert.annotate(drawn.withColumn("entity", F.lit("it"))), threshold=cfg.rl.length_threshold, max_tokens=cfg.sft.max_tokens)
    kept, rest = write_stage(drawn.select("sample_id", "x").join(said, "sample_id"), "retained"), write_stage(rest, "rest")
    policy, losses = train_sft(kept, new_policy(), epochs or cfg.sft.epochs, cfg.engine.sft, cfg.sft.warmup, batch=effective_batch(cfg.sft), seed=cfg.seed)
    return policy, kept, rest, losses


def train_staged(spark, sf_dir: str, cfg: Config | None = None, stages: int = 2, strategy: str = "progressive", sft_epochs: int | None = None, rl_epochs: int | None = None, max_steps: int | None = None, feats: DataFrame | None = None, cold_start: bool = True, run_dir: str | None = None) -> Trained:
    """Both stages, or the first alone; without ``cold_start`` the second begins from an untrained policy, on the same rest."""
    cfg, seconds, began = cfg or Config(), {}, time.time()
    feats = features(spark, sf_dir) if feats is None else feats
    seconds["features"] = time.time() - began
    began = time.time()
    if cold_start:
        policy, _, rest, losses = stage_one(feats, cfg, sft_epochs)
    else:
        rest = write_stage(sampling.stratified_draw(feats.where("split = 'train'"), frac=cfg.sft.fraction, seed=cfg.seed)[1], "rest")
        policy, losses = new_policy(), []
    seconds["stage1"] = time.time() - began
    if stages == 1:
        return Trained(policy, policy, losses, None, None, seconds)
    began = time.time()
    pools = write_stage(schedule.split_by_difficulty(rest, predict(rest, policy)), "pools", ("pool",))
    none_share = feats.where("split = 'train'").agg(F.avg((F.col("gold") == NONE).cast("double"))).first()[0] or 0.0
    final, log = train_rl(feats, pools, policy, none_share, cfg, strategy, rl_epochs, max_steps=max_steps, run_dir=run_dir)
    seconds["stage2"] = time.time() - began
    return Trained(final, policy, losses, pools, log, seconds)
