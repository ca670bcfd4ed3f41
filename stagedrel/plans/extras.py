"""Queries of the surrounding operators: joins, windows, rollups, hygiene, vectors, JSON, streams and trained runs."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.labels import NONE
from ..ontology import LABELS, load_ontology
from ..operators import metrics as M
from ..sources import tables as T
from ..sources.io import write_stage
from ..streaming import rewards as S
from . import ablation
from .oracle_views import using
from .workloads import predictions

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None, *views: str):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLE_SQL[f.__name__] = using(*views, query=sql)
        return f

    return add


# --- the reward log -------------------------------------------------------------------------------------------


def _events(spark, d):
    return T.table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def _naive(df, *names):
    """Back to times without a zone (sessions may differ in theirs)."""
    return df.withColumns({n: F.date_format(n, "yyyy-MM-dd HH:mm:ss") for n in names})


_STAMP = "strftime({}, '%Y-%m-%d %H:%M:%S')"


@query(f"SELECT {_STAMP.format('s')} AS start, n, round(r, 6) AS reward FROM (SELECT date_trunc('day', ts) AS s, count(*) AS n, avg(value) AS r FROM events GROUP BY 1)")
def reward_curve_tumbling(spark, d):
    return _naive(S.reward_curve(_events(spark, d)), "start")


@query(f"SELECT {_STAMP.format('s')} AS start, count(*) AS n, round(avg(value), 6) AS reward FROM (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 12 HOUR, date_trunc('day', ts) + INTERVAL 12 HOUR]) AS s, ts, value FROM events) WHERE ts >= s AND ts < s + INTERVAL 1 DAY GROUP BY s")
def reward_curve_sliding(spark, d):
    return _naive(S.reward_curve(_events(spark, d), slide="12 hours"), "start")


@query(f"""SELECT user_id, {_STAMP.format('min(ts)')} AS start, count(*) AS n, round(avg(value), 6) AS reward FROM (SELECT *, sum(is_new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (
  SELECT *, (lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL OR ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 2 HOUR)::INT AS is_new FROM events)) GROUP BY user_id, s""")
def reward_sessions(spark, d):
    return _naive(S.reward_sessions(_events(spark, d)), "start")


@query("SELECT event_id, user_id, round(value - lag(value) OVER (PARTITION BY user_id ORDER BY ts, event_id), 6) AS delta FROM events")
def reward_delta_lag(spark, d):
    o = W.partitionBy("user_id").orderBy("ts", "event_id")
    return _events(spark, d).select("event_id", "user_id", F.round(F.col("value") - F.lag("value").over(o), 6).alias("delta"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS moving, round(avg(value) OVER (PARTITION BY user_id ORDER BY epoch(date_trunc('second', ts))::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW), 6) AS day FROM events")
def moving_reward(spark, d):
    e = _events(spark, d).withColumn("sec", F.unix_timestamp("ts"))
    rows = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    span = W.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)
    return e.select("event_id", F.round(F.avg("value").over(rows), 6).alias("moving"), F.round(F.avg("value").over(span), 6).alias("day"))


@query("SELECT user_id, round(regr_slope(value, epoch(date_trunc('second', ts)) / 86400.0::DOUBLE), 4) AS slope FROM events GROUP BY user_id")
def reward_slope(spark, d):
    return _events(spark, d).groupBy("user_id").agg(F.round(F.regr_slope(F.col("value"), F.unix_timestamp("ts") / 86400.0), 4).alias("slope"))


@query("SELECT e.event_id, (SELECT max(struct_pack(t := s.ts, i := s.event_id)).i FROM events s WHERE s.event_type = 'signup' AND s.user_id = e.user_id AND s.ts <= e.ts) AS version_id FROM events e WHERE e.event_type <> 'signup'")
def asof_policy_version(spark, d):
    """As-of join: the last signup of the same user before each event, by one window over both sides."""
    o = W.partitionBy("user_id").orderBy("ts", F.col("kind"), "event_id").rowsBetween(W.unboundedPreceding, 0)
    e = _events(spark, d).withColumn("kind", (F.col("event_type") != "signup").cast("int"))
    v = F.last(F.when(F.col("kind") == 0, F.col("event_id")), ignorenulls=True).over(o)
    return e.withColumn("version_id", v).where("kind = 1").select("event_id", "version_id")


@query("SELECT a.event_id AS prompt_id, b.event_id AS answer_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def interval_pairs(spark, d):
    """Interval join by time blocks of the interval's length: each answer meets the prompts of its block and the one before."""
    e = _events(spark, d).withColumn("block", F.floor(F.unix_timestamp("ts") / 3600))
    p = e.where("event_type = 'click'").select(F.col("event_id").alias("prompt_id"), "user_id", F.col("ts").alias("pts"), F.explode(F.array("block", F.col("block") + 1)).alias("block"))
    a = e.where("event_type = 'purchase'").select(F.col("event_id").alias("answer_id"), "user_id", F.col("ts").alias("ats"), "block")
    return p.join(a, ["user_id", "block"]).where("ats >= pts and ats <= pts + interval 1 hour").select("prompt_id", "answer_id")


@query("SELECT event_id, (props::JSON ->> 'k')::BIGINT AS k, (props::JSON ->> 'k')::BIGINT % 7 AS bucket FROM events")
def props_json(spark, d):
    v = F.try_variant_get(F.try_parse_json("props"), "$.k", "bigint")
    return T.table(spark, d, "events").select("event_id", v.alias("k"), (v % 7).alias("bucket"))


# --- samples, measures and dimensions -------------------------------------------------------------------------


@query("SELECT s.sample_id, c.cell FROM samples s JOIN (SELECT unnest(range(64)) AS cell) c ON c.cell % 8 >= x0 AND c.cell % 8 < x0 + 4 AND c.cell // 8 >= y0 AND c.cell // 8 < y0 + 4", "samples")
def box_range_join(spark, d):
    """Range join box-contains-cell, turned into an equi-join by giving out each box's cells."""
    s = T.build_samples(spark, d).select("sample_id", "box")
    at = F.explode(F.sequence(F.lit(0), F.lit(15)))
    s = s.withColumn("i", at).select("sample_id", ((F.col("box.y0") + F.expr("i div 4")) * 8 + F.col("box.x0") + F.col("i") % 4).cast("long").alias("cell"))
    return s.join(F.broadcast(spark.range(64).select(F.col("id").alias("cell"))), "cell").select("sample_id", "cell")  # 64 rows


_FACTS = "(SELECT p.method, s.obj_type, s.split, (p.gold = p.pred)::INT AS hit FROM preds p JOIN (SELECT sample_id, obj_type, split FROM samples) s USING (sample_id))"


def _facts(spark, d):
    s = T.build_samples(spark, d).select("sample_id", "obj_type", "split")
    return predictions(spark, d).join(s, "sample_id").withColumn("hit", (F.col("gold") == F.col("pred")).cast("int"))


@query(f"SELECT coalesce(method, 'all') AS method, coalesce(obj_type, 'all') AS obj_type, count(*) AS n, sum(hit)::BIGINT AS hits, grouping_id(method, obj_type)::BIGINT AS g FROM {_FACTS} GROUP BY CUBE (method, obj_type)", "preds", "samples")
def metrics_cube(spark, d):
    c = _facts(spark, d).cube("method", "obj_type").agg(F.count("*").alias("n"), F.sum("hit").alias("hits"), F.grouping_id().cast("long").alias("g"))
    return c.withColumns({x: F.coalesce(x, F.lit("all")) for x in ("method", "obj_type")})


@query("SELECT coalesce(r_name, 'all') AS r_name, coalesce(n_name, 'all') AS n_name, count(*) AS customers, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)")
def metrics_rollup(spark, d):
    c, n, r = (T.table(spark, d, t) for t in ("customer", "nation", "region"))
    both = c.join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
    out = both.rollup("r_name", "n_name").agg(F.count("*").alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance"))
    return out.withColumns({x: F.coalesce(x, F.lit("all")) for x in ("r_name", "n_name")})


@query("SELECT sample_id, ntile(4) OVER (PARTITION BY obj_type ORDER BY hits, sample_id)::BIGINT AS quarter FROM (SELECT p.sample_id, s.obj_type, sum((p.gold = p.pred)::INT)::BIGINT AS hits FROM preds p JOIN (SELECT sample_id, obj_type FROM samples) s USING (sample_id) GROUP BY ALL)", "preds", "samples")
def difficulty_ntile(spark, d):
    h = _facts(spark, d).groupBy("sample_id", "obj_type").agg(F.sum("hit").alias("hits"))
    return h.select("sample_id", F.ntile(4).over(W.partitionBy("obj_type").orderBy("hits", "sample_id")).cast("long").alias("quarter"))


@query("SELECT vec_id, other, round(c, 6) AS cosine FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY c DESC, other) AS rn FROM (SELECT a.vec_id, b.vec_id AS other, list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) / sqrt(list_dot_product(a.embedding::DOUBLE[], a.embedding::DOUBLE[]) * list_dot_product(b.embedding::DOUBLE[], b.embedding::DOUBLE[])) AS c FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0)) WHERE rn <= 3")
def vector_cosine_topk(spark, d):
    """Nearest vectors of the same label for a stated query set (ids divisible by 50), against all rows."""
    from ..operators.vectors import nearest

    return nearest(T.table(spark, d, "embeddings"), F.col("vec_id") % 50 == 0, 3)


@query("SELECT d.doc_id, b.item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def leak_guard(spark, d):
    """Exact passages of the benchmark in documents, wherever they begin and end.

    The words inside a passage (without its first and last, which may be joined to other signs) stand in a document as
    they are: an equi-join on the hash of up to four of them, then the whole passage. Passages without an inner word
    are few and short: they are broadcast and looked for in each text.
    """
    docs, items = T.table(spark, d, "documents").select("doc_id", "text"), T.table(spark, d, "benchmark").select("item_id", F.col("text").alias("passage"))
    words = F.split("passage", r"\s+")
    items = items.where("passage is not null").withColumn("inner", F.when(F.size(words) > 2, F.slice(words, 2, F.least(F.size(words) - 2, F.lit(4)))).otherwise(F.array().cast("array<string>")))
    items = write_stage(items.withColumn("m", F.size("inner")), "passages")
    run = lambda m: F.array_distinct(F.transform(F.when(F.size("w") >= m, F.sequence(F.lit(1), F.size("w") - (m - 1))).otherwise(F.array().cast("array<int>")), lambda i: F.xxhash64(F.slice("w", i, m))))
    out = None
    for m in sorted(r["m"] for r in items.select("m").distinct().collect()):  # 0 to 4
        own = items.where(F.col("m") == m)
        if m == 0:
            met = docs.join(F.broadcast(own), F.contains("text", F.col("passage")))  # a stated set of short passages against all texts
        else:
            w = docs.select("doc_id", F.split("text", r"\s+").alias("w"))
            spots = w.select("doc_id", F.explode(run(m)).alias("h"))
            hit = spots.join(own.select("item_id", F.xxhash64("inner").alias("h")), "h").select("doc_id", "item_id").distinct()
            met = hit.join(docs, "doc_id").join(own.select("item_id", "passage"), "item_id").where(F.contains("text", F.col("passage")))
        met = met.select("doc_id", "item_id")
        out = met if out is None else out.union(met)
    return docs.select("doc_id", F.lit(None).cast("long").alias("item_id")).limit(0) if out is None else out


@query("SELECT md5(text) AS h, count(*) AS n, min(doc_id) AS first_doc FROM documents GROUP BY 1 HAVING count(*) > 1")
def duplicate_texts(spark, d):
    g = T.table(spark, d, "documents").groupBy(F.md5(F.col("text").cast("binary")).alias("h")).agg(F.count("*").alias("n"), F.min("doc_id").alias("first_doc"))
    return g.where("n > 1")


@query("SELECT lang, source, count(*) AS n, sum(n_chars)::BIGINT AS chars, max(n_chars) AS longest FROM documents GROUP BY ALL")
def source_profile(spark, d):
    return T.table(spark, d, "documents").groupBy("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"), F.max("n_chars").alias("longest"))


@query("SELECT 'quality' AS method, round(avg((quality = toxic)::INT::DOUBLE), 6) AS acc, round(sum(quality * toxic)::DOUBLE / sum(quality), 6) AS p, round(sum(quality * toxic)::DOUBLE / sum(toxic), 6) AS r FROM labels")
def binary_measures(spark, d):
    t = T.table(spark, d, "labels")
    both = F.sum(F.col("quality") * F.col("toxic"))
    return t.agg(F.round(F.avg((F.col("quality") == F.col("toxic")).cast("double")), 6).alias("acc"), F.round(F.try_divide(both, F.sum("quality")), 6).alias("p"), F.round(F.try_divide(both, F.sum("toxic")), 6).alias("r")).withColumn("method", F.lit("quality"))


_SAYS = {k: LABELS[i] for i, k in enumerate(("AF", "AO", "NF", "RF", "RO"))} | {"NO": NONE}
_SAID = "CASE {} " + " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in _SAYS.items()) + " END"


def _published_sql(a: str, b: str) -> str:
    x, y = ablation.PUBLISHED[a], ablation.PUBLISHED[b]
    published = " UNION ALL ".join(f"SELECT '{m}' AS metric, round({x[i]}::DOUBLE / {y[i]} - 1, 6) AS published" for i, m in enumerate(("acc", "p", "r", "f1")))
    return f"""SELECT metric, gain, published FROM ({published}) JOIN (
      SELECT metric, round(max(value) FILTER (method = 'formed') / nullif(max(value) FILTER (method = 'long'), 0) - 1, 6) AS gain FROM (UNPIVOT (
        SELECT method, round(a, 6) AS acc, round(coalesce(p, 0), 6) AS p, round(coalesce(r, 0), 6) AS r, round(coalesce(2 * p * r / nullif(p + r, 0), 0), 6) AS f1 FROM (
          SELECT method, avg((pred IS NOT DISTINCT FROM gold)::INT::DOUBLE) AS a, sum((pred = gold AND gold <> 'none')::INT)::DOUBLE / nullif(sum((pred <> 'none')::INT), 0) AS p, sum((pred = gold AND gold <> 'none')::INT)::DOUBLE / nullif(sum((gold <> 'none')::INT), 0) AS r FROM (
            SELECT 'formed' AS method, {_SAID.format("gold")} AS gold, CASE WHEN r_format = 1 THEN {_SAID.format("answer")} ELSE 'none' END AS pred FROM tabular UNION ALL
            SELECT 'long', {_SAID.format("gold")}, CASE WHEN r_length = 1 THEN {_SAID.format("answer")} ELSE 'none' END FROM tabular) GROUP BY method)) ON acc, p, r, f1 INTO NAME metric VALUE value) GROUP BY metric) USING (metric)"""


@query(_published_sql("full", "classifier_7"), "tabular")
def published_gain(spark, d):
    """The gain of well-formed over long responses in the logged groups of orders, next to the published gain of the full run."""
    says = F.create_map(*[F.lit(x) for kv in _SAYS.items() for x in kv])
    said = lambda c: F.try_element_at(says, F.col(c))
    t = T.tabular_groups(spark, d).select(said("gold").alias("gold"), said("answer").alias("answer"), "r_format", "r_length")
    kept = F.explode(F.array(F.struct(F.lit("formed").alias("method"), (F.col("r_format") == 1).alias("on")), F.struct(F.lit("long").alias("method"), (F.col("r_length") == 1).alias("on"))))
    preds = t.withColumn("m", kept).select("m.method", "gold", F.when(F.col("m.on"), F.col("answer")).otherwise(NONE).alias("pred"))
    published = M.relative_gain(ablation.published(spark), "full", "classifier_7").withColumnRenamed("gain", "published")
    return M.relative_gain(M.accuracy_prf(preds), "formed", "long").join(F.broadcast(published), "metric").select("metric", "gain", "published")  # four rows


# --- streams --------------------------------------------------------------------------------------------------


def _stream(spark, d, parts: int = 3, flush: bool = True):
    """The events as a stream of files in order of time: one file is written after the other, as a stream reads them by age.

    ``flush`` adds a last file with one event far ahead (of no user, id -1), which carries the watermark past all others.
    """
    folder = _folder(spark)
    events = T.table(spark, d, "events").withColumn("sec", F.unix_timestamp(F.col("ts").cast("timestamp")))
    low, high = events.agg(F.min("sec"), F.max("sec")).first()
    for k in range(parts) if low is not None else ():
        a, b = (low + (high + 1 - low) * x // parts for x in (k, k + 1))
        events.where((F.col("sec") >= a) & (F.col("sec") < b)).drop("sec").coalesce(1).write.mode("append").parquet(folder)
    last = events.drop("sec").limit(1).withColumns({"ts": F.lit("2200-01-01 00:00:00").cast("timestamp_ntz"), "event_id": F.lit(-1).cast("long"), "user_id": F.lit(-1).cast("long"), "event_type": F.lit("end")})
    if flush:
        for _ in range(2):  # the second lets the first one's watermark act
            last.coalesce(1).write.mode("append").parquet(folder)
    return S.event_stream(spark, folder)


def _folder(spark):
    import uuid

    from ..sources.io import stage_dir

    return f"{stage_dir(spark)}/events-{uuid.uuid4().hex}"


@query(ORACLE_SQL["reward_curve_tumbling"])
def reward_curve_stream(spark, d):
    """Windows of a stream that has ended; each equals the batch window."""
    return _naive(S.run_to_end(S.reward_curve(_stream(spark, d))).where("start < '2200-01-01'"), "start")


@query("SELECT sample_id, k, size = 8 AS complete, round(CASE WHEN sd <= 1e-12 THEN 0 ELSE (value - mean) / sd END, 6) AS adv FROM (SELECT *, count(*) OVER w AS size, avg(value) OVER w AS mean, stddev_pop(value) OVER w AS sd FROM (SELECT user_id AS sample_id, event_id AS k, value, (row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1) // 8 AS g FROM events) WINDOW w AS (PARTITION BY sample_id, g))")
def group_completion_stream(spark, d):
    """Every response of the stream: in full groups, and what is left at its end."""
    r = _stream(spark, d).select(F.col("user_id").alias("sample_id"), F.col("event_id").alias("k"), F.col("value").alias("reward"), "ts")
    return S.run_to_end(S.complete_groups(r, 8, timeout_ms=400 * 86_400_000)).where("sample_id >= 0")


@query()
def late_data(spark, d):
    """Events that come once their window is closed are dropped: rows counted by the stream, and in all."""
    e = T.table(spark, d, "events")
    folder = _folder(spark)
    e.where("event_id % 10 <> 0").coalesce(1).write.parquet(folder)
    e.where("event_id % 10 = 0").coalesce(1).write.mode("append").parquet(folder)
    got = S.run_to_end(S.reward_curve(S.event_stream(spark, folder)))
    return got.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("counted")).crossJoin(e.agg(F.count("*").alias("events")))  # one row each


@query("SELECT event_id FROM events")
def stream_dedup(spark, d):
    return S.run_to_end(S.deduplicated(_stream(spark, d, flush=False)).select("event_id"))


@query("SELECT event_id, label FROM events JOIN ontology ON seq = event_id % 21", "ontology")
def stream_ontology(spark, d):
    return S.run_to_end(S.with_labels(_stream(spark, d, flush=False), load_ontology(spark)).select("event_id", "label"))


@query(ORACLE_SQL["interval_pairs"])
def stream_interval(spark, d):
    e = _stream(spark, d, flush=False)
    return S.run_to_end(S.matched_responses(e.where("event_type = 'click'"), e.where("event_type = 'purchase'")))


# --- trained runs ---------------------------------------------------------------------------------------------


@query("SELECT e AS epoch, ceil(n / 128.0)::INT AS steps, n AS rows, true AS loss_falls FROM (SELECT count(*) AS n FROM samples WHERE split = 'train'), (SELECT unnest(range(20))::INT AS e)", "samples")
def sft_train(spark, d):
    """Supervised steps of an epoch over all training rows, and whether the mean loss of the last epoch is below the first's."""
    from ..config import SftConfig, effective_batch
    from ..policy import training as tr

    train = tr.features(spark, d).where("split = 'train'")
    n, batch = train.count(), effective_batch(SftConfig())
    _, losses = tr.train_sft(train, tr.new_policy(), batch=batch)
    return spark.createDataFrame([(e, -(-n // batch), n, losses[-1] < losses[0]) for e in range(len(losses))], "epoch int, steps int, rows long, loss_falls boolean")


@query()
def label_only_sft(spark, d):
    from ..policy import training as tr

    f = tr.features(spark, d)
    policy, _ = tr.train_sft(f.where("split = 'train'"), tr.new_policy(True))
    return M.accuracy_prf(tr.predict(f.where("split = 'test'"), policy).withColumn("method", F.lit("label_only_100")))


@query()
def closed_head(spark, d):
    from ..operators.baselines import VIEWS
    from ..operators.baselines import closed_head as fit
    from ..policy import training as tr

    f = tr.features(spark, d)
    train, test = f.where("split = 'train'"), f.where("split = 'test'")
    return M.accuracy_prf(reduce(DataFrame.unionByName, [fit(train, test, v).withColumn("method", F.lit(v)) for v in VIEWS]))


@query("SELECT 'closed_all' AS method, 0 AS new_label_answers", "samples")
def closed_label_limit(spark, d):
    """A closed head never says a label that it was not trained on."""
    return ablation.closed_label_limit(spark, d).where("method = 'closed_all'").select("method", "new_label_answers")


@query()
def added_label_answers(spark, d):
    return ablation.closed_label_limit(spark, d)


_QUOTA = "(SELECT t, ceil(128 * r / (1 + r) - 1e-9)::BIGINT AS qe, ceil(128 / (1 + r) - 1e-9)::BIGINT AS qh, r FROM (SELECT t, 0.5::DOUBLE ** (t - 1) AS r FROM (SELECT unnest([1, 2, 3, 4]) AS t)))"


@query(f"""SELECT t::INT AS epoch, s::INT AS step, greatest(0, least(qe, e - s * qe))::BIGINT AS easy, greatest(0, least(qh, h - s * qh))::BIGINT AS hard, 8 * (greatest(0, least(qe, e - s * qe)) + greatest(0, least(qh, h - s * qh)))::BIGINT AS responses,
  round(least(1.0, g / greatest(1, floor(0.05 * max(g) OVER ()))), 9)::DOUBLE AS lr FROM (SELECT *, row_number() OVER (ORDER BY t, s) AS g FROM (
  SELECT *, unnest(range(greatest(ceil(h / qh::DOUBLE), ceil(e / qe::DOUBLE))::BIGINT)) AS s FROM (SELECT t, qe, qh, h, least(floor(h * r + 0.5), a)::BIGINT AS e FROM {_QUOTA}, (SELECT count(*) FILTER (pool = 'hard') AS h, count(*) FILTER (pool = 'easy') AS a FROM pools))))""", "pools")
def rl_train(spark, d):
    """All steps of four epochs of updates on pools by hash: what each batch holds, and the learning rate's course."""
    from ..operators import sampling
    from ..policy import training as tr

    f = tr.features(spark, d)
    train = f.where("split = 'train'")
    pools = write_stage(ablation.skill_pools(sampling.stratified_draw(train.select("sample_id", "gold"))[1]), "pools", ("pool",))
    share = train.agg(F.avg((F.col("gold") == NONE).cast("double"))).first()[0] or 0.0
    _, log = tr.train_rl(f, pools, tr.new_policy(), share)
    rows = [(x["epoch"], x["step"], x["easy"], x["hard"], x["responses"], round(x["lr"], 9)) for x in log.steps]
    return spark.createDataFrame(rows, "epoch int, step int, easy long, hard long, responses long, lr double")


@query()
def staged_end_to_end(spark, d):
    from ..policy import training as tr

    f = tr.features(spark, d)
    run = tr.train_staged(spark, d, feats=f)
    test = f.where("split = 'test'")
    both = tr.predict(test, run.stage1).withColumn("method", F.lit("stage_1")).unionByName(tr.predict(test, run.policy).withColumn("method", F.lit("full")))
    return M.accuracy_prf(both)


@query()
def main_comparison(spark, d):
    return M.accuracy_prf(ablation.main_comparison(spark, d)).withColumn("framework", ablation.framework(F.col("method")))


@query()
def ablation_mix(spark, d):
    return ablation.mix_ablation(spark, d)


@query()
def stage_toggles(spark, d):
    return ablation.stage_toggles(spark, d)


@query("SELECT method, used, (SELECT count(*) FROM cold) AS train, round(used::DOUBLE / (SELECT count(*) FROM cold), 6) AS share FROM (VALUES ('label_only_100', (SELECT count(*) FROM cold)), ('label_only_25', (SELECT count(*) FROM cold WHERE drawn)), ('stage_1', (SELECT count(*) FROM reasoned WHERE reason = 'ok'))) AS x(method, used)", "cold", "reasoned")
def label_usage(spark, d):
    """Training rows whose labels a method learns from, and their share."""
    from .workloads import _cold, _reasoned, _train

    n = lambda df, name: df.agg(F.lit(name).alias("method"), F.count("*").alias("used"))
    used = n(_train(spark, d), "label_only_100").union(n(_cold(spark, d)[0], "label_only_25")).union(n(_reasoned(spark, d).where("reason = 'ok'"), "stage_1"))
    return used.withColumn("train", F.max("used").over(W.partitionBy())).withColumn("share", F.round(F.col("used") / F.col("train"), 6))  # a row a method


_HARD = "(SELECT count(*) FROM pools WHERE pool = 'hard')"


@query(f"SELECT s AS strategy, t::INT AS epoch, (CASE WHEN s = 'raw' THEN (SELECT count(*) FROM pools WHERE pool = 'easy') WHEN s = 'equal' THEN least({_HARD}, (SELECT count(*) FROM pools WHERE pool = 'easy')) WHEN s = 'hard_only' THEN 0 ELSE floor({_HARD} * 0.5::DOUBLE ** (t - 1) + 0.5) END)::BIGINT AS easy, {_HARD} AS hard FROM (SELECT unnest(['raw', 'equal', 'hard_only', 'progressive']) AS s), (SELECT unnest([1, 2, 3, 4]) AS t)", "pools")
def mix_composition(spark, d):
    from ..operators import sampling

    train = write_stage(T.build_samples(spark, d).where("split = 'train'").select("sample_id", "gold"), "train")
    pools = write_stage(ablation.skill_pools(sampling.stratified_draw(train)[1]), "pools", ("pool",))
    share = train.agg(F.avg((F.col("gold") == NONE).cast("double"))).first()[0] or 0.0
    c = ablation.composition(pools, share)
    wide = c.groupBy("strategy", "epoch").pivot("pool", ["easy", "hard"]).agg(F.sum("rows"))
    return wide.select("strategy", "epoch", *[F.coalesce(x, F.lit(0)).cast("long").alias(x) for x in ("easy", "hard")])


# --- aggregates and functions of users ------------------------------------------------------------------------


@query("SELECT event_type, count(*) AS n, arg_max(event_id, struct_pack(v := value, i := event_id)) AS best, arg_min(event_id, struct_pack(v := value, i := event_id)) AS worst, round(stddev_samp(value), 6) AS spread, count(DISTINCT user_id) AS users, sum((value > 50)::INT)::BIGINT AS above FROM events GROUP BY event_type")
def reward_profile(spark, d):
    e = T.table(spark, d, "events")
    at = F.struct("value", "event_id")
    return e.groupBy("event_type").agg(F.count("*").alias("n"), F.max_by("event_id", at).alias("best"), F.min_by("event_id", at).alias("worst"), F.round(F.stddev_samp("value"), 6).alias("spread"), F.count_distinct("user_id").alias("users"), F.count_if(F.col("value") > 50).alias("above"))


@query()
def reward_sketches(spark, d):
    """Approximate quantiles, distinct counts and histograms of the log: one pass of mergeable aggregates."""
    e = T.table(spark, d, "events")
    return e.groupBy("event_type").agg(F.percentile_approx("value", [0.5, 0.9], 1000).alias("quantiles"), F.approx_count_distinct("user_id", 0.02).alias("users"), F.histogram_numeric("value", F.lit(8)).alias("histogram"), F.mode("user_id").alias("busiest"))


@query("SELECT sample_id, round(stddev_pop(reward), 6) AS spread FROM rewarded GROUP BY sample_id", "rewarded")
def spread_by_udaf(spark, d):
    from ..functions.udfs import group_spread
    from .workloads import _rewarded

    return _rewarded(spark, d).groupBy("sample_id").agg(group_spread()("reward").alias("spread"))


@query()
def policy_scores(spark, d):
    from ..functions.udfs import policy_score
    from ..policy import training as tr

    return tr.features(spark, d).select("sample_id", F.round(policy_score(tr.new_policy(), F.col("x")), 6).alias("score"))


@query("SELECT DISTINCT lang, source FROM documents WHERE n_chars > 1024 INTERSECT SELECT lang, source FROM documents WHERE n_chars <= 1024")
def length_overlap(spark, d):
    """Set operations: language and source pairs with texts on both sides of the length threshold."""
    t = T.table(spark, d, "documents")
    return t.where("n_chars > 1024").select("lang", "source").intersect(t.where("n_chars <= 1024").select("lang", "source"))


@query("SELECT event_id, rank() OVER w AS place, round(percent_rank() OVER w, 6) AS share FROM events WINDOW w AS (PARTITION BY event_type ORDER BY value)")
def reward_ranks(spark, d):
    w = W.partitionBy("event_type").orderBy("value")
    return T.table(spark, d, "events").select("event_id", F.rank().over(w).cast("long").alias("place"), F.round(F.percent_rank().over(w), 6).alias("share"))


@query("SELECT 'except' AS op, lang FROM (SELECT lang FROM documents EXCEPT ALL SELECT lang FROM documents WHERE n_chars > 1024) UNION ALL SELECT 'intersect' AS op, lang FROM (SELECT lang FROM documents WHERE n_chars > 1024 INTERSECT ALL SELECT lang FROM documents WHERE n_chars > 4096)")
def multiset_operations(spark, d):
    t = T.table(spark, d, "documents").select("lang", "n_chars")
    long, longer = (t.where(F.col("n_chars") > n).select("lang") for n in (1024, 4096))
    return t.select("lang").exceptAll(long).select(F.lit("except").alias("op"), "lang").union(long.intersectAll(longer).select(F.lit("intersect").alias("op"), "lang"))


@query("SELECT method, gold, pred, levenshtein(gold, pred) AS distance FROM preds GROUP BY ALL", "preds")
def label_distance(spark, d):
    """How far an answer's spelling is from the gold label's, for each pair that occurs."""
    return predictions(spark, d).select("method", "gold", "pred").distinct().withColumn("distance", F.levenshtein("gold", "pred").cast("long"))


@query("SELECT gold, sum((method = 'strong' AND pred = gold)::INT)::BIGINT - sum((method = 'weak' AND pred = gold)::INT)::BIGINT AS more FROM preds GROUP BY gold", "preds")
def class_gain_maps(spark, d):
    """Right answers of one method over another, class by class, as maps side by side."""
    hits = predictions(spark, d).groupBy("method", "gold").agg(F.sum((F.col("pred") == F.col("gold")).cast("long")).alias("n"))
    maps = hits.groupBy().agg(*[F.map_from_entries(F.collect_list(F.when(F.col("method") == m, F.struct("gold", "n")))).alias(m) for m in ("strong", "weak")])  # a row a label
    gain = F.map_zip_with("strong", "weak", lambda k, a, b: F.coalesce(a, F.lit(0)) - F.coalesce(b, F.lit(0)))
    return maps.select(F.explode(gain).alias("gold", "more"))


@query("SELECT o_orderkey, o_orderdate, datediff('day', o_orderdate, max(l_shipdate))::INT AS days, date_trunc('month', o_orderdate)::DATE::VARCHAR AS month FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey, o_orderdate")
def order_spans(spark, d):
    o, li = T.table(spark, d, "orders").select("o_orderkey", "o_orderdate"), T.table(spark, d, "lineitem").select("l_orderkey", "l_shipdate")
    last = li.groupBy("l_orderkey").agg(F.max("l_shipdate").alias("last"))
    both = o.join(last, o.o_orderkey == last.l_orderkey)
    return both.select("o_orderkey", "o_orderdate", F.datediff("last", "o_orderdate").alias("days"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month"))
