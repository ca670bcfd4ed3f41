"""Worked examples of the method's definitions, and its invariants."""

import math
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from stagedrel import sql_api
from stagedrel.config import RlConfig, SftConfig, effective_batch
from stagedrel.functions import labels, prompts, responses, rewards
from stagedrel.functions import objective as O
from stagedrel.functions.portable import hash_hex
from stagedrel.ontology import LABELS, candidates, load_ontology, recompose
from stagedrel.operators import metrics as M
from stagedrel.operators import sampling, schedule
from stagedrel.plans import ablation, assertions, extras, workloads
from stagedrel.policy import softmax
from stagedrel.policy import training as tr
from stagedrel.sources import io, tables

SF = "/root/testdata/sf0.001"


def one(spark, column, **given):
    return spark.range(1).select(*[F.lit(v).alias(k) for k, v in given.items()]).select(column.alias("x")).first()["x"]


def response(order=(1, 2, 3, 4, 5, 6), answer="none", pad=""):
    steps = "\n".join(f"Step {k}: s{pad}" for k in order)
    return f"<think>{steps}\n</think>" + ("" if answer is None else f"<answer>{answer}</answer>")


@pytest.mark.parametrize(("text", "want"), [
    (response(), 1.0), (response((1, 2, 3, 4, 6, 5)), 0.0), (response((1, 2, 3, 4, 5)), 0.0), (response((1, 1, 2, 3, 4, 5, 6)), 0.0), (response(answer="no/such"), 0.0),
    (response(answer=None), 0.0), ("", 0.0), (None, 0.0), (response(answer="/per/org/member_of"), 1.0), ("<think></think><answer>none</answer>", 0.0),
    ("<think> Step 1:a Step 2:b Step 3:c Step 4:d Step 5:e Step 6:f </think> <answer>none</answer>", 1.0), ("\n " + response() + " \n", 1.0),
    ("so " + response(), 0.0), (response() + " so", 0.0), (response(answer=None) + " so <answer>none</answer>", 0.0), ("<answer>none</answer>" + response(answer=None), 0.0),
    (response() + "<answer>/per/per/peer</answer>", 0.0), ("<think>well, Step 1:a Step 2:b Step 3:c Step 4:d Step 5:e Step 6:f</think><answer>none</answer>", 0.0), ("<think>" + response(), 0.0),
])
def test_format_reward(spark, text, want):
    assert one(spark, rewards.format_reward(F.lit(text).cast("string"), workloads.label_array())) == want


def test_parsed_steps(spark):
    got = one(spark, responses.parse_response(F.lit("<think> Step 1:a b Step 2:\nc Step 3: d\ne Step 4: Step 5:x Step 6:y </think>\n<answer> none </answer>")))
    assert list(got["steps"]) == ["a b", "c", "d\ne", "", "x", "y"] and got["answer"] == "none" and got["well_formed"] and got["order"] == "1,2,3,4,5,6"
    two = one(spark, responses.parse_response(F.lit(response() + "<answer>none</answer>")))
    assert two["answer"] == "" and not two["well_formed"]


def test_passages_are_found_wherever_they_stand(spark, tmp_path):
    from stagedrel.plans import extras

    docs = [(1, 'he said "the old boat is here"'), (2, "the old boat"), (3, "nothing"), (4, "xthe old boaty"), (5, "an old bo"), (6, None), (7, "the old  boat is here")]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    items = [(1, "the old boat is here"), (2, "the old boat"), (3, "old bo"), (4, "boat"), (5, None), (6, "not there at all by any means")]
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = {tuple(r) for r in extras.leak_guard(spark, str(tmp_path)).collect()}
    assert got == {(d, i) for d, t in docs for i, p in items if t is not None and p is not None and p in t}


def test_length_and_answer_rewards(spark):
    assert [one(spark, rewards.length_reward(F.lit("x" * n))) for n in (1024, 1025)] == [0.0, 1.0]
    assert [one(spark, rewards.length_reward(F.lit("x " * n), 3, "token")) for n in (3, 4)] == [0.0, 1.0]
    assert one(spark, rewards.answer_reward(F.lit(None).cast("string"), F.lit("none"))) == 0.0
    with pytest.raises(ValueError):
        rewards.length_reward(F.lit(""), unit="line")


def test_advantages(spark):
    def nested(*r, ddof=0):
        return one(spark, O.advantage_nested(F.array(*[F.lit(float(x)) for x in r]), ddof))

    assert nested(3, 1) == [1, -1] and nested(2, 2, 2) == [0, 0, 0] and nested(3) == [0] and nested(3, ddof=1) == [0]
    a = nested(0, 1, 3, 2, 2)
    assert abs(sum(a)) < 1e-9 and abs(sum(x * x for x in a) - 5) < 1e-9 and max(map(abs, a)) <= 2 + 1e-9


def test_objective_terms(spark):
    for ratio, adv, want in ((1.5, 1, 1.2), (0.5, -1, -0.8), (1.5, -1, -1.5), (0.5, 1, 0.5), (1, 0.7, 0.7)):
        assert abs(one(spark, O.clipped_term(F.lit(ratio), F.lit(float(adv)))) - want) < 1e-12
    for x, want in ((1, 0.0), (2, 1 - math.log(2)), (0.5, math.log(2) - 0.5)):
        assert abs(one(spark, O.divergence_term(F.lit(0.0), F.lit(math.log(x)))) - want) < 1e-12
    assert abs(one(spark, O.sequence_nll(F.array(F.lit(-1.0), F.lit(-0.5)))) - 1.5) < 1e-12


def test_schedule():
    assert [schedule.mix_ratio(t) for t in (1, 2, 3, 4)] == [1, 0.5, 0.25, 0.125]
    assert [schedule.batch_quota(16, t) for t in (1, 2, 3, 4)] == [(8, 8), (6, 11), (4, 13), (2, 15)]
    assert [schedule.batch_quota(128, t) for t in (1, 2, 3, 4)] == [(64, 64), (43, 86), (26, 103), (15, 114)]
    assert [sum(schedule.batch_quota(16, t, fit="trim")) for t in (1, 2, 3, 4)] == [16] * 4
    assert schedule.mix_ratio(3, strategy="equal") == 1 and schedule.batch_quota(16, 1, strategy="hard_only") == (0, 16)
    assert [math.ceil(2370 / schedule.batch_quota(128, t)[1]) for t in (1, 2, 3, 4)] == [38, 28, 24, 21]
    assert [2370 * schedule.mix_ratio(t) for t in (1, 2, 3, 4)] == [2370, 1185, 592.5, 296.25]
    for alpha in (0, -1, 1.5):
        with pytest.raises(ValueError):
            schedule.mix_ratio(1, alpha)
    with pytest.raises(ValueError):
        schedule.mix_ratio(1, strategy="raw")
    assert effective_batch(SftConfig()) == 128 == effective_batch(RlConfig())
    assert [tr.warmup_lr(s, 100, 1.0) for s in (0, 4, 50)] == [0.2, 1.0, 1.0]


def test_pools_of_epochs(spark):
    rows = [(i, "none" if i % 4 else "/per/per/peer", "hard" if i % 5 == 0 else "easy") for i in range(1000)]
    pools = spark.createDataFrame(rows, "sample_id long, gold string, pool string")
    for t in (1, 2):
        got = schedule.epoch_pool(pools, t, 0.6).collect()
        hard, easy = [r for r in got if r["pool"] == "hard"], [r for r in got if r["pool"] == "easy"]
        assert sorted(r["sample_id"] for r in hard) == list(range(0, 1000, 5))
        assert len(easy) == 200 / t and abs(sum(r["gold"] == "none" for r in easy) - 0.6 * len(easy)) <= 1
    short = schedule.epoch_pool(pools.where("pool = 'hard' or sample_id % 4 <> 0"), 1, 0.6).where("pool = 'easy'")
    assert short.count() == 200  # no real easy row is left: none rows fill in
    assert schedule.epoch_pool(pools, 1, 0.6, strategy="hard_only").count() == 200 and schedule.epoch_pool(pools, 3, 0.6, strategy="raw").count() == 1000
    first, third = ({r["sample_id"] for r in schedule.epoch_pool(pools, t, 0.6, nested=True).collect()} for t in (1, 3))
    assert third <= first
    easy, hard = schedule.batch_quota(16, 1)
    dealt = schedule.assign_batches(schedule.epoch_pool(pools, 1, 0.6), easy, hard, 1)
    sizes = dealt.groupBy("step", "pool").count().where("step < 25").collect()
    assert len(sizes) == 50 and all(r["count"] == 8 for r in sizes)
    assert dealt.groupBy("step").agg((F.max("slot") + 1 == F.count("*")).alias("ok")).where("not ok").count() == 0


def test_draws(spark):
    df = spark.range(5000).select(F.col("id").alias("sample_id"), F.when(F.col("id") % 100 == 0, "rare").when(F.col("id") == 1, "single").otherwise("common").alias("gold"))
    for rounding, n in (("half_up", 13), ("floor", 12), ("ceil", 13)):
        drawn, rest = sampling.stratified_draw(df, rounding=rounding)
        counts = {r["gold"]: r["count"] for r in drawn.groupBy("gold").count().collect()}
        assert counts["rare"] == n and counts["single"] == 1 and drawn.count() + rest.count() == 5000
    a, b = (sorted(r["sample_id"] for r in sampling.stratified_draw(df.repartition(n))[0].collect()) for n in (1, 17))
    assert a == b
    ranked = sampling.hash_rank(df, hash_hex(1, "x", F.col("sample_id")), ["sample_id"]).orderBy(hash_hex(1, "x", F.col("sample_id"))).collect()
    assert [r["rank"] for r in ranked] == list(range(5000))
    with pytest.raises(ValueError):
        sampling.quota(F.lit(1), 0.5, "up")


def test_ontology_and_prompts(spark):
    o = load_ontology(spark)
    assert o.count() == 21 == len(LABELS)
    by = {(r["obj_type"], r["ent_type"]): r["labels"] for r in candidates(o).collect()}
    assert len(by) == 16 and len(by[("per", "org")]) == 4 and all("none" in v for v in by.values())
    hint = lambda g: one(spark, prompts.answer_hint(F.lit(g)))
    assert not any(x.split("/")[-1] in hint("none") for x in LABELS[:-1]) and "member_of" in hint("/per/org/member_of")
    learner = one(spark, prompts.learner_prompt(LABELS, F.lit("t"), F.lit("e")))
    assert "Hint" not in learner and "Step 1" not in learner and all(x in learner for x in LABELS)
    assert "Step 3" not in prompts.step_guide([1, 2]) and prompts.step_guide().count("Step ") == 6
    assert one(spark, labels.split_label(F.lit("bad/label"))["obj_type"]) is None
    assert candidates(load_ontology(spark, extra=[("loc", "per", "home_of")])).where("obj_type = 'loc' and ent_type = 'per'").first()["labels"] == ["/loc/per/home_of", "none"]


def test_measures(spark):
    p = spark.createDataFrame([("m", 1, "none", "none"), ("m", 2, "none", LABELS[0]), ("m", 3, LABELS[0], LABELS[0]), ("m", 4, LABELS[1], "none")], "method string, sample_id long, gold string, pred string")
    assert tuple(M.accuracy_prf(p).first()) == ("m", 0.5, 0.5, 0.5, 0.5)
    odd = p.union(spark.createDataFrame([("m", 5, LABELS[0], "garbage")], p.schema))
    assert M.accuracy_prf(odd).first()["p"] == 0.5 and abs(M.accuracy_prf(odd).first()["r"] - 1 / 3) < 1e-6
    micro = M.averaged_prf(p, "micro").first()
    assert micro["p"] == micro["r"] == micro["f1"] == 0.5
    unanswered = p.union(spark.createDataFrame([("m", 6, "none", None)], p.schema))
    assert M.averaged_prf(unanswered, "micro").first()["p"] == 0.4
    with pytest.raises(ValueError):
        M.averaged_prf(p, "mean")


def test_published_table(spark):
    for _, (acc, p, r, f1) in ablation.PUBLISHED.items():
        assert abs(2 * p * r / (p + r) - f1) < 0.04
    gain = lambda a, b: {r["metric"]: round(100 * r["gain"], 1) for r in M.relative_gain(ablation.published(spark), a, b).collect()}
    assert gain("full", "classifier_7") == {"acc": 1.5, "p": 4.2, "r": 8.0, "f1": 6.1}
    assert gain("full", "label_only_100") == {"acc": 2.7, "p": 19.6, "r": 7.7, "f1": 13.8}
    assert gain("stage_1", "label_only_100") == {"acc": 0.8, "p": 13.5, "r": -3.1, "f1": 5.3}


def test_gradient_is_the_objective_s_slope():
    rng = np.random.default_rng(0)
    policy = tr.new_policy()
    policy.theta += rng.standard_normal(policy.theta.shape) * 0.3
    old, ref = policy.copy(), policy.copy()
    ref.theta = ref.theta + rng.standard_normal(ref.theta.shape) * 0.05
    x = rng.standard_normal((40, softmax.WIDTH)) * 0.5
    u = softmax.uniforms_of(range(40), policy.heads)
    taken, lp_old = old.steps(x, softmax.sampler(0.8, u))
    on = {h: np.maximum(v, 0) for h, v in taken.items()}
    assert np.allclose(policy.replay(x, on), lp_old)
    adv, lp_ref = rng.standard_normal(40), ref.replay(x, on)
    policy.theta += rng.standard_normal(policy.theta.shape) * 0.02

    import pandas as pd

    batch = pd.DataFrame({"x": list(x), "outcomes": list(np.stack([taken[h] for h in policy.heads], axis=1)), "adv": adv, "lp_old": lp_old, "lp_ref": lp_ref})

    def value(p):
        out = next(softmax.update_partial(p, 0.2, 0.1)(iter([batch])))
        return out.loc[out["i"] == -1, "g"].item(), out["g"].to_numpy()[:-2].reshape(p.theta.shape)

    _, g = value(policy)
    for k in rng.choice(policy.theta.size, 25, replace=False):
        a, b = policy.copy(), policy.copy()
        a.theta.ravel()[k] += 1e-5
        b.theta.ravel()[k] -= 1e-5
        assert abs((value(a)[0] - value(b)[0]) / 2e-5 - g.ravel()[k]) < 1e-5


def test_what_the_responses_teach(spark):
    rows = [(1, "/per/org/member_of", "per", "org"), (2, "none", "loc", None)]
    drawn = spark.createDataFrame(rows, "sample_id long, gold string, obj_type string, ent_type string").withColumn("entity", F.lit("it"))
    text = [(r["sample_id"], r["gold"], "<think>Step 1: x Step 2: related " + ("no" if r["gold"] == "none" else "yes") + f" Step 3: y Step 4: types {r['obj_type']} and misc Step 5: z Step 6: w</think><answer>{r['gold']}</answer>") for r in drawn.collect()]
    text += [(3, "none", "<answer>none</answer>"), (4, "none", text[0][2])]
    got = {r["sample_id"]: tuple(r)[1:] for r in tr.taught_by(spark.createDataFrame(text, "sample_id long, gold string, response string")).collect()}
    assert got == {1: ("/per/org/member_of", "per", "misc", 1, 1), 2: ("none", "loc", "misc", 1, 0)}  # types as the text says them
    long = tr.taught_by(tr.expert.annotate(drawn.withColumn("sample_id", F.col("sample_id") + 100)))
    assert all(r["style"] == 0 for r in long.collect())
    assert tr.taught_by(spark.createDataFrame(text[:1], "sample_id long, gold string, response string"), max_tokens=5).count() == 0


def test_supervised_batches(spark):
    f = tr.features(spark, SF).where("split = 'train'").limit(300).cache()
    chain, a = tr.train_sft(f, tr.new_policy(), 2, 0.05)
    jobs, b = tr.train_sft(f.repartition(7), tr.new_policy(), 2, 0.05, distributed=True)
    assert np.allclose(chain.theta, jobs.theta) and np.allclose(a, b) and a[1] < a[0]
    part, _ = tr.train_sft(f, chain, 1, 0.05, trainable=["label"])
    moved = {h: not np.array_equal(part.theta[s], chain.theta[s]) for h, s in chain.heads.items()}
    assert moved == {h: h == "label" for h in chain.heads}


def test_training(spark, tmp_path):
    f = tr.features(spark, SF)
    run = tr.train_staged(spark, SF, rl_epochs=1, feats=f)
    assert run.losses[-1] < run.losses[0]
    assert run.pools.count() == run.pools.select("sample_id").distinct().count()
    hard = run.pools.where("pool = 'hard'").count()
    assert sum(x["hard"] for x in run.log.steps) == hard and all(x["hard"] <= 64 and x["easy"] <= 64 for x in run.log.steps)
    test = f.where("split = 'test'")
    m = {k: M.accuracy_prf(tr.predict(test, p).withColumn("method", F.lit(k))).first() for k, p in (("untrained", tr.new_policy()), ("full", run.policy))}
    assert m["full"]["f1"] >= m["untrained"]["f1"] and m["full"]["acc"] > 0.5
    again = tr.generate(test.repartition(5), run.policy, 3, 0.8, "s").select("sample_id", "k", "response")
    assert sorted(map(tuple, again.collect())) == sorted(map(tuple, tr.generate(test.coalesce(1), run.policy, 3, 0.8, "s").select("sample_id", "k", "response").collect()))
    drawn = tr.train_rl(f, run.pools, run.stage1, 0.7, epochs=1, max_steps=1, mode="step_draw")
    assert drawn[1].steps[0]["responses"] > 0
    # a chain makes the updates that jobs of each step make
    chained, line = tr.train_rl(f, run.pools, run.stage1, 0.7, epochs=1, max_steps=2)
    jobs, steps = tr.train_rl(f, run.pools, run.stage1, 0.7, epochs=1, max_steps=2, distributed=True)
    assert np.allclose(chained.theta, jobs.theta, atol=1e-9) and not np.allclose(chained.theta, run.stage1.theta)
    assert [x.keys() == y.keys() and all(x[c] == pytest.approx(y[c]) for c in x) for x, y in zip(line.steps, steps.steps, strict=True)] == [True] * len(line.steps)
    # a run that is cut off goes on where it was
    whole, log = tr.train_rl(f, run.pools, run.stage1, 0.7, epochs=2, max_steps=3)
    folder = f"file://{tmp_path}/run"
    tr.train_rl(f, run.pools, run.stage1, 0.7, epochs=2, max_steps=2, run_dir=folder)
    resumed, rest = tr.train_rl(f, run.pools, run.stage1, 0.7, epochs=2, max_steps=3, run_dir=folder)
    assert np.allclose(resumed.theta, whole.theta) and [x["step"] for x in rest.steps] == [x["step"] for x in log.steps] and len(rest.steps) == min(3, len(log.steps))


@pytest.mark.parametrize("max_tokens", [1024, 12])
def test_rewards_of_a_text_in_memory_equal_the_columns(spark, max_tokens):
    from stagedrel.policy.softmax import text_rewards

    good, labels = response(), workloads.label_array()
    texts = [good, f"  {good}\n", good.replace("\n", " "), "x" + good, good + "x", good + "<answer>none</answer>", good.replace("Step 2", "Step 7"), good.replace("</think>", ""), good.replace("</think>", "</think> so "), good.replace("<think>", "<think> and "), "", "<answer>none</answer>", "<think> </think><answer></answer>", good.replace("none", "other")]
    df = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "k int, t string").withColumn("t2", responses.truncate_tokens(F.col("t"), max_tokens))
    want = df.select("k", rewards.format_reward(F.col("t2"), labels), rewards.length_reward(F.col("t2"), 90), responses.parse_response(F.col("t2"))["answer"]).orderBy("k").collect()
    assert [tuple(r)[1:] for r in want] == [text_rewards(t, frozenset(LABELS), 90, max_tokens) for t in texts]


def test_new_label_is_a_new_row(spark):
    got = {r["method"]: r for r in ablation.closed_label_limit(spark, SF).collect()}
    assert got["closed_all"]["new_label_answers"] == 0 and got["policy"]["gold_rows"] > 0 and got["policy"]["right"] <= got["policy"]["new_label_answers"]
    p = tr.new_policy().with_label("/loc/per/home_of", "loc", "per")
    assert p.rows == tr.new_policy().rows + 1 and p.allowed[2, 0].sum() == 1


def test_sql_surface(spark):
    sql_api.register_sql(spark, SF)
    got = spark.sql("SELECT sample_id, k, format_reward(response) + length_reward(response, 1024) + answer_reward(answer_of(response), gold) AS reward FROM rollouts")
    assert sorted(map(tuple, got.collect())) == sorted((r["sample_id"], r["k"], r["reward"]) for r in workloads.total_reward(spark, SF).collect())
    assert not assertions.has_python(got)
    plan = spark.sql("SELECT * FROM batch_plan(128, 0.5D, 4, 2370)").collect()
    assert [tuple(r) for r in plan] == [(1, 64, 64, 38), (2, 43, 86, 28), (3, 26, 103, 24), (4, 15, 114, 21)]
    assert spark.sql("SELECT count(*) FROM rollouts, LATERAL steps_of(response)").first()[0] > 0
    x = spark.sql("SELECT clipped_term(1.5D, 1D, 0.2D), divergence_term(0D, 0D), policy_ratio(0D, 0D), mix_ratio(3, 0.5D)").first()
    assert tuple(x) == (1.2, 0.0, 1.0, 0.25)


def test_plans(spark):
    t = workloads.objective_lineitem(spark, SF)
    assert not assertions.has_python(t) and not assertions.has_cross_join(t)
    scans = assertions.read_columns(t)
    assert all("l_shipdate" not in s and "o_totalprice" not in s for s in scans)
    nested = spark.range(10).select(F.array(F.lit(1.0), F.lit(2.0)).alias("r")).select(O.advantage_nested(F.col("r")))
    assert assertions.shuffles(nested) == 0
    assert "assistant" in assertions.pushed_filters(workloads.format_reward(spark, SF))
    assert assertions.shuffles(workloads.cold_draw_bernoulli(spark, SF)) <= 1


def test_stage_tables(spark, tmp_path):
    df = spark.createDataFrame([(1, "a"), (2, "b")], "id long, v string")
    path = f"file://{tmp_path}/t"
    assert io.append_new(df, path, ["id"]) == 2 and io.append_new(df, path, ["id"]) == 0
    assert io.append_new(df.withColumn("id", F.col("id") + 1), path, ["id"]) == 1
    io.export_chat_lines(df.selectExpr("v as line"), f"file://{tmp_path}/lines")
    io.export_report(df, f"file://{tmp_path}/csv")
    assert spark.read.text(f"file://{tmp_path}/lines").count() == 2
    assert io.binary_pictures(spark, f"file://{tmp_path}/lines").count() >= 1
    assert one(spark, responses.truncate_tokens(F.lit("a b c"), 2)) == "a b"


def test_prompt_shards(spark, tmp_path):
    from stagedrel.plans import workloads as w
    from stagedrel.sources.prompt_shards import PromptShards

    io.export_chat_lines(w.chat_export(spark, SF).repartition(3), f"file://{tmp_path}/shards")
    spark.dataSource.register(PromptShards)
    got = spark.read.format("prompt_shards").load(f"file://{tmp_path}/shards")
    assert got.count() == 2 * w.chat_export(spark, SF).count() and {r["role"] for r in got.select("role").distinct().collect()} == {"user", "assistant"}


def test_sketches_and_scores(spark):
    from stagedrel.plans import extras

    exact = {r["event_type"]: r for r in extras.reward_profile(spark, SF).collect()}
    for r in extras.reward_sketches(spark, SF).collect():
        assert abs(r["users"] - exact[r["event_type"]]["users"]) <= 0.1 * exact[r["event_type"]]["users"] and len(r["histogram"]) == 8
    assert extras.policy_scores(spark, SF).where("score > 0").count() == 0


def test_seeds_and_neutral_labels(spark):
    got = {r["method"]: r for r in ablation.over_seeds(spark, SF, seeds=(1, 2), neutral=True, rl_epochs=1, max_steps=1).collect()}
    assert set(got) == {"stage_1", "full"} and all(r["seeds"] == 2 and 0 <= r["f1_mean"] <= 1 for r in got.values())


def _days(spark):
    """Orders of each day and the quarter, counted by hand."""
    return Counter(r[0].date() for r in spark.read.parquet(f"{SF}/orders.parquet").select(F.col("o_orderdate").cast("timestamp")).collect())


def test_quotas_of_the_orders_days(spark):
    days = _days(spark)
    want = {(d, n, a, *schedule.batch_quota(n, (d.month + 2) // 3, a)) for d, n in days.items() for a in (0.25, 0.5, 1.0)}
    got = workloads.QUERIES["batch_quota_table"](spark, SF).collect()
    assert len(got) == 3 * len(days) and {(r["day"], r["batch"], r["alpha"], r["easy"], r["hard"]) for r in got} == want


def test_trimmed_quotas_fill_the_orders_days(spark):
    days = _days(spark)
    want = {(d, a, *schedule.batch_quota(n, (d.month + 2) // 3, a, "trim")) for d, n in days.items() for a in (0.25, 0.5, 1.0)}
    got = workloads.QUERIES["batch_quota_trim"](spark, SF).collect()
    assert len(got) == 3 * len(days) and {(r["day"], r["alpha"], r["easy"], r["hard"]) for r in got} == want and all(r["easy"] + r["hard"] == r["batch"] for r in got)


def test_every_sample_s_label_goes_round(spark):
    got = workloads.QUERIES["label_roundtrip"](spark, SF).collect()
    assert len(got) == tables.build_samples(spark, SF).count() > 500 and all(r["label"] == r["again"] for r in got)
    assert len({r["label"] for r in got}) > 10 and all(r["again"] == r["label"] for r in recompose(load_ontology(spark).select("label")).collect())


def test_ratios_of_the_orders_quarters(spark):
    n = Counter()
    for day, priority in spark.read.parquet(f"{SF}/orders.parquet").select(F.col("o_orderdate").cast("timestamp"), "o_orderpriority").collect():
        n[day.year, (day.month + 2) // 3, priority[0] in "12"] += 1
    want = {(y, t, a, schedule.mix_ratio(t, a), min(n[y, t, False], math.floor(n[y, t, True] * schedule.mix_ratio(t, a) + 0.5))) for y, t, _ in n for a in (0.25, 0.5, 1.0)}
    got = workloads.QUERIES["mix_ratio_table"](spark, SF).collect()
    assert len(got) == len(want) and {(r["year"], r["t"], r["alpha"], r["ratio"], r["drawn"]) for r in got} == {(y, t, a, round(r, 6), k) for y, t, a, r, k in want}


def test_every_sample_has_its_candidates(spark):
    got = workloads.QUERIES["ontology_candidates"](spark, SF).collect()
    assert len(got) == tables.build_samples(spark, SF).count() > 500
    for r in got:
        want = [x for x in LABELS if x.startswith(f"/{r['obj_type']}/{r['ent_type']}/")] + ["none"]
        assert r["labels"].split(",") == want and r["n"] == len(want)


def test_gain_over_the_logged_lines(spark):
    rows = tables.tabular_groups(spark, SF).select("answer", "gold", "r_format", "r_length").collect()
    acc = [sum(("NO" if not r[k] else r["answer"]) == r["gold"] for r in rows) for k in ("r_format", "r_length")]
    got = {r["metric"]: r for r in extras.QUERIES["published_gain"](spark, SF).collect()}
    assert set(got) == {"acc", "p", "r", "f1"} and abs(got["acc"]["gain"] - (acc[0] / acc[1] - 1)) < 1e-4 and len(rows) > 5000
    assert {m: round(100 * r["published"], 1) for m, r in got.items()} == {"acc": 1.5, "p": 4.2, "r": 8.0, "f1": 6.1}


def test_rates_of_the_users_events(spark):
    runs: dict = {}
    for user, _, event in sorted(map(tuple, spark.read.parquet(f"{SF}/events.parquet").select("user_id", "ts", "event_id").collect())):
        runs.setdefault(user, []).append(event)
    want = {e: (s, tr.warmup_lr(s, len(run), 1e-4)) for run in runs.values() for s, e in enumerate(run)}
    got = workloads.QUERIES["warmup_table"](spark, SF).collect()
    assert len(got) == len(want) and all(r["step"] == want[r["event_id"]][0] and abs(r["lr"] - want[r["event_id"]][1]) < 1e-15 for r in got)


def test_warmup_column_equals_the_function(spark):
    got = spark.range(300).select("id", schedule.warmup(F.col("id"), F.lit(300), 1e-4, 0.05).alias("lr")).collect()
    assert all(abs(r["lr"] - tr.warmup_lr(r["id"], 300, 1e-4, 0.05)) < 1e-15 for r in got)
