"""Reading tables, and the sample view built of them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.labels import NONE
from ..functions.portable import hash_hex
from ..functions.regions import block_mean, crop_region
from ..ontology import RELATIONS, TYPES

#: Splits by image at the published shares, as the first hex digits of a hash.
TRAIN_BELOW, DEV_BELOW = "c395", "d99a"
LANG_TYPE = {"en": "org", "fr": "per", "de": "loc", "es": "misc"}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _type_of(index):
    return F.get(F.array(*[F.lit(t) for t in TYPES]), index)


def build_samples(spark: SparkSession, sf_dir: str, boxes: int = 4, seed: int = 42) -> DataFrame:
    """A row per image and object box: image, box, crop, text, entity, types, gold label, split.

    One equi-join on the image's id (Spark broadcasts or shuffles by size); everything else is a projection.
    """
    images = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("image"))
    texts = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("vec_id"), "text", "lang")
    s = images.join(texts, "vec_id").withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(boxes - 1))))
    s = s.withColumns({"x0": ((F.col("vec_id") + F.col("j")) % 5).cast("int"), "y0": ((F.expr("vec_id div 5") + 2 * F.col("j")) % 5).cast("int")})
    s = s.withColumn("crop", crop_region(F.col("image"), F.col("x0"), F.col("y0")))
    cp = [block_mean(F.col("crop"), r, c, 4) for r in (0, 2) for c in (0, 2)]
    pooled = {k: block_mean(F.col("image"), 2 * (k // 4), 2 * (k % 4), 8) for k in (0, 5, 10)}
    lang = F.create_map(*[F.lit(x) for kv in LANG_TYPE.items() for x in kv])
    s = s.withColumns({
        "sample_id": F.col("vec_id") * boxes + F.col("j"),
        "obj_type": _type_of(2 * (cp[0] >= 0).cast("int") + (cp[3] >= 0).cast("int")),
        "ent_type": F.try_element_at(lang, F.col("lang")),
        "entity": F.regexp_extract("text", "[A-Za-z]{4,}", 0),
        "_real": (pooled[0] + cp[1]) > 0.03,
        "_which": 2 * (pooled[5] >= 0).cast("int") + (pooled[10] >= 0).cast("int"),
    })
    pairs = F.create_map(*[x for o, e, rs in RELATIONS for x in (F.lit(f"{o}/{e}"), F.array(*[F.lit(f"/{o}/{e}/{r}") for r in rs]))])
    own = F.try_element_at(pairs, F.concat_ws("/", "obj_type", "ent_type"))
    prefix = F.substring(hash_hex(seed, "split", F.col("vec_id")), 1, 4)
    return s.withColumn("_own", own).select(
        "sample_id", "vec_id", "image", F.struct("x0", "y0", F.lit(4).alias("w"), F.lit(4).alias("h")).alias("box"), "crop", "text", "entity", "ent_type", "obj_type",
        F.when(F.col("_real") & F.col("_own").isNotNull(), F.get("_own", F.col("_which") % F.size("_own"))).otherwise(NONE).alias("gold"),
        F.when(prefix < TRAIN_BELOW, "train").when(prefix < DEV_BELOW, "dev").otherwise("test").alias("split"),
    )


def page_regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages as another carrier: the first paragraph element as a box of characters [start, end), and its crop."""
    pages = table(spark, sf_dir, "pages")
    start = F.instr("html", "<p>") - 1
    tail = F.when(start >= 0, F.substring("html", start + 1, F.length("html")))
    end = F.when(start >= 0, start + F.instr(F.coalesce(tail, F.lit("")), "</p>") + 3)
    return pages.select("page_id", start.alias("box_start"), end.alias("box_end"), F.when(end > start, F.substring("html", start + 1, end - start)).alias("crop"), F.size(F.regexp_extract_all("html", F.lit("<[a-zA-Z][^>]*>"), F.lit(0))).alias("n_tags"))


def logged_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Logged responses: the assistant turns of a conversation are one group; a fixed rule wraps them in the template and damages some."""
    from ..ontology import LABELS

    turns = table(spark, sf_dir, "conversations").where("role = 'assistant'")
    pick = F.array(*[F.lit(x) for x in LABELS])
    from ..functions.portable import hash_int

    gold = F.get(pick, (hash_int(7, "gold", F.col("conv_id")) % len(LABELS)).cast("int"))
    other = F.get(pick, (hash_int(7, "pred", F.col("conv_id"), F.col("turn")) % len(LABELS)).cast("int"))
    fault = F.substring(hash_hex(7, "fault", F.col("conv_id"), F.col("turn")), 1, 2)
    t = turns.select("conv_id", "turn", "text", gold.alias("gold"), F.when(fault < "90", gold).otherwise(other).alias("said"), fault.alias("fault"))
    steps = F.concat(*[F.concat(F.lit(f"Step {k}: "), F.regexp_replace("text", "[\n<>]", " ") if k == 1 else F.lit("noted"), F.lit("\n")) if k != 3 else F.when(F.col("fault").between("20", "3f"), "").otherwise("Step 3: noted\n") for k in range(1, 7)])
    body = F.concat(F.lit("<think>"), steps, F.lit("</think>"), F.when(F.col("fault") < "10", "").otherwise(F.concat(F.lit("<answer>"), F.col("said"), F.lit("</answer>"))))
    old = -(F.length("text") % 97) / 50.0 - 0.5
    return t.select(
        F.col("conv_id").alias("sample_id"), F.col("turn").alias("k"), "gold", body.alias("response"),
        old.alias("lp_old"), (old + ((F.col("turn") * 7 + F.col("conv_id")) % 11 - 5) / 20.0).alias("lp_cur"), (old + ((F.col("turn") * 3 + F.col("conv_id")) % 7 - 3) / 25.0).alias("lp_ref"),
    )


def tabular_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ragged groups at scale: a question is an order, a response one of its lines."""
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_orderstatus", "o_orderpriority")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_returnflag", "l_linestatus", "l_extendedprice", "l_quantity", "l_discount", "l_tax")
    both = lines.join(orders, "l_orderkey")
    pred = F.concat("l_returnflag", "l_linestatus")
    gold = F.concat(F.when(F.substring("o_orderpriority", 1, 1) <= "2", "A").when(F.substring("o_orderpriority", 1, 1) <= "3", "N").otherwise("R"), F.when(F.col("o_orderstatus") == "P", "O").otherwise(F.col("o_orderstatus")))
    old = -F.col("l_quantity") / 50
    return both.select(
        F.col("l_orderkey").alias("sample_id"), F.col("l_linenumber").cast("long").alias("k"), pred.alias("answer"), gold.alias("gold"),
        (F.col("l_linenumber") <= 5).cast("double").alias("r_format"), (F.col("l_extendedprice") > 30000).cast("double").alias("r_length"), (pred == gold).cast("double").alias("r_answer"),
        old.alias("lp_old"), (old + (F.col("l_discount") - 0.05) * 4).alias("lp_cur"), (old + (F.col("l_tax") - 0.04) * 2).alias("lp_ref"),
    )


def order_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(day, batch, t): the orders as a run of batches. A step takes a day's orders, an epoch is a quarter of a year."""
    days = table(spark, sf_dir, "orders").groupBy(F.col("o_orderdate").cast("date").alias("day")).agg(F.count("*").alias("batch"))
    return days.withColumn("t", F.quarter("day"))


def order_pools(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(year, t, easy, hard): orders of each quarter, an epoch. Urgent and high ones are hard."""
    hard = F.coalesce(F.sum((F.substring("o_orderpriority", 1, 1) <= "2").cast("long")), F.lit(0).cast("long"))
    by = table(spark, sf_dir, "orders").groupBy(F.year("o_orderdate").alias("year"), F.quarter("o_orderdate").alias("t"))
    return by.agg((F.count("*") - hard).alias("easy"), hard.alias("hard"))
