"""Embedding near-dedup by sorted projection passes.

In each pass the vectors of a label are put in the lexicographic order of concatenated random hashes (signs of random
projections), and every vector is compared with its ``window`` neighbours in that order; verified pairs of all passes
are united. Where more vectors than the window holds share a key prefix (loose groups), the rest of that run is
compared tile against tile. So a pair has been compared after a pass in which it shares the prefix, whatever the
group's size, and the number of passes follows from the target recall for a pair at the threshold.

Runs of near-equal vectors are collapsed before: vectors with equal hash keys join a ball around one of them if they
lie within half the threshold angle (less the roundings), which proves that all of the ball are linked with each other,
so their links are counted without comparing them. A pair of balls is linked as a whole, not at all, or, where the
triangle inequality leaves it open, compared vector by vector.

Defined results: vectors are compared within equal labels and equal lengths; null labels and vectors that are null,
empty, zero, or that hold null or non-finite components link with nothing; repeated ids are vectors of their own that
report the same component; ids of any type and size come back as they are; other columns play no part; an empty table
gives an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import kernels
from .common import components, materialize, small

ROUNDING = 1e-7


def prefix_bits(n: int, window: int) -> int:
    """Bits of a key prefix that n evenly spread vectors share by half a window."""
    return max(1, math.ceil(math.log2(max(2, n) / window)) + 1)


def passes_for(n: int, window: int, cosine: float, recall: float) -> int:
    """Passes after which a pair at the threshold has shared a prefix with the target recall among n vectors of a label."""
    meet = (1 - math.acos(cosine) / math.pi) ** prefix_bits(n, window)
    return max(2, math.ceil(math.log(1 - recall) / math.log(1 - meet)))


def vector_links(vectors: DataFrame, cosine: float = 0.93, window: int = 128, recall: float = 0.97, rounds: int = 2, tile: int = 256, seed: int = 11, id_col: str = "vec_id", vec_col: str = "embedding", label_col: str = "label") -> DataFrame:
    """A row per row of vectors: id, n_links (other rows linked directly), component_id (smallest id reachable), kept."""
    theta = math.acos(cosine)
    single = vectors.schema[vec_col].dataType.simpleString() == "array<float>"
    kind = "<f4" if single else "<f8"  # vectors travel in the table's own precision
    rows = vectors.select(F.col(id_col).alias("id"), F.col(label_col).cast("string").alias("label"), F.col(vec_col).cast("array<float>" if single else "array<double>").alias("vec"))
    most = rows.where("label is not null").groupBy("label").count().agg(F.max("count").alias("m")).first()["m"] or 0
    passes, key_bits = passes_for(most, window, cosine, recall), min(60, 4 + max(12, math.ceil(math.log2(most + 2))))
    id_type = vectors.schema[id_col].dataType.simpleString()
    ready = materialize(rows.mapInArrow(kernels.vector_rows(kind, rounds, key_bits, passes, seed), f"id {id_type}, label string, node string, raw binary, near array<long>, keys array<long>"), "vectors")
    base = ready.where("node <> ''").groupBy("node").agg(F.first("label").alias("label"), F.first("raw").alias("raw"), F.first("near").alias("near"), F.first("keys").alias("keys"), F.count("*").alias("size"), F.min("id").alias("low"))
    nodes = materialize(base, "vector-nodes")

    # balls of vectors that are certainly linked with each other
    balls = nodes.select(F.col("node").alias("ball"), "label", "raw", "near", "keys", F.lit(0.0).alias("radius"), "size", "low")
    member = nodes.select("node", F.col("node").alias("ball"))
    for r in range(rounds):
        keyed = balls.withColumn("k", F.get("near", F.lit(r)))
        pivot = keyed.groupBy("label", "k").agg(F.max(F.struct("size", "ball")).alias("top"), F.count("*").alias("n")).where("n > 1").select("label", "k", F.col("top.ball").alias("pivot"))
        pivot = pivot.join(balls.select(F.col("ball").alias("pivot"), F.col("raw").alias("pivot_raw")), "pivot")
        near = keyed.join(pivot, ["label", "k"]).select("ball", "pivot", "raw", "pivot_raw", "radius")
        near = near.mapInPandas(kernels.ball_rows(kind, theta / 2 - ROUNDING), "ball string, pivot string, reach double")
        moved = materialize(near, "vector-moves")
        whole = balls.join(moved, "ball", "left").withColumns({"to": F.coalesce("pivot", "ball"), "reach": F.coalesce("reach", "radius")})
        grown = whole.groupBy("to").agg(F.max("reach").alias("radius"), F.sum("size").alias("size"), F.min("low").alias("low"))
        balls = materialize(grown.join(balls.select(F.col("ball").alias("to"), "label", "raw", "near", "keys"), "to").select(F.col("to").alias("ball"), "label", "raw", "near", "keys", "radius", "size", "low"), "vector-balls")
        member = member.join(moved.select("ball", "pivot"), "ball", "left").select("node", F.coalesce("pivot", "ball").alias("ball"))
    member = materialize(member, "vector-members")

    # exact ranks in the order of each pass: position in a sorted partition plus the rows of those before it
    spots = balls.select("ball", "label", F.posexplode("keys").alias("pass", "k"))
    order = ["pass", "label", "k", "ball"]
    placed = materialize(spots.repartitionByRange(*order).sortWithinPartitions(*order).select("pass", "ball", F.monotonically_increasing_id().alias("m")), "vector-order")
    part = F.shiftrightunsigned("m", 33)
    before = placed.groupBy(part.alias("part")).agg(F.count("*").alias("n")).withColumn("before", F.sum("n").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)))
    placed = placed.withColumn("part", part).join(before.select("part", F.coalesce("before", F.lit(0)).alias("before")), "part")
    ranks = placed.groupBy("ball").agg(F.sort_array(F.collect_list(F.struct("pass", (F.col("before") + F.col("m").bitwiseAND((1 << 33) - 1)).alias("rank")))).alias("r")).select("ball", F.col("r.rank").alias("ranks"))
    span, shift = 4 * window, 60 - prefix_bits(most, window)
    runs = F.transform("keys", lambda k: F.shiftright(k, shift))
    laid = balls.join(ranks, "ball").select("ball", "label", "raw", "radius", "size", "ranks", runs.alias("runs"))
    laid = materialize(laid, "vector-laid")
    each = laid.select("*", F.posexplode("ranks").alias("pass", "rank"))
    own = F.expr(f"rank div {span}")
    # neighbour tiles: their own rows (part 1) and the window before them (part 0)
    tiled = each.withColumn("g", F.explode(F.when(F.col("rank") % span >= span - window, F.array(own, own + 1)).otherwise(F.array(own))))
    tiled = tiled.select(F.lit(-1).cast("long").alias("a"), F.lit(-1).cast("long").alias("b"), "g", (own == F.col("g")).cast("int").alias("part"), "ball", "label", "raw", "radius", "size", "ranks", "runs", "pass", "rank")
    # run tiles: what a window can't hold of the rows with one prefix
    spot = laid.select("label", F.posexplode("runs").alias("pass", "run"), F.col("ranks").alias("rs")).select("label", "pass", "run", F.get("rs", F.col("pass")).alias("rank"))
    long = spot.groupBy("label", "pass", "run").agg(F.min("rank").alias("g"), F.count("*").alias("n")).where(F.col("n") > window)
    long = small(materialize(long.select("label", "pass", "run", "g", F.ceil(F.col("n") / F.lit(tile)).cast("long").alias("tiles")), "vector-runs"))
    held = each.withColumn("run", F.get("runs", F.col("pass"))).join(long, ["label", "pass", "run"]).withColumn("own", F.expr(f"(rank - g) div {tile}"))
    held = held.withColumn("o", F.explode(F.sequence(F.lit(0).cast("long"), F.col("tiles") - 1)))
    held = held.select(F.least("own", "o").alias("a"), F.greatest("own", "o").alias("b"), "g", F.col("own").cast("int").alias("part"), "ball", "label", "raw", "radius", "size", "ranks", "runs", "pass", "rank")
    found = tiled.unionByName(held).groupBy("a", "b", "g").applyInPandas(kernels.pass_tile(cosine, kind, window, ROUNDING), "u string, v string, links long, kind string")
    found = materialize(found, "vector-links")

    # pairs of balls that are neither linked as a whole nor apart: vector by vector, tile against tile
    open_pairs = found.where("kind = 'open'").select("u", "v")
    held = member.join(nodes.select("node", "raw", "size"), "node")
    tiles = member.groupBy("ball").agg(F.ceil(F.count("*") / F.lit(tile)).cast("long").alias("tiles"))
    sided = open_pairs.join(tiles.select(F.col("ball").alias("u"), F.col("tiles").alias("ut")), "u").join(tiles.select(F.col("ball").alias("v"), F.col("tiles").alias("vt")), "v")
    left = sided.join(held.withColumnRenamed("ball", "u"), "u").select("u", "v", F.lit(0).alias("side"), F.pmod(F.xxhash64("node"), F.col("ut")).alias("a"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("vt") - 1)).alias("b"), "node", "raw", "size")
    right = sided.join(held.withColumnRenamed("ball", "v"), "v").select("u", "v", F.lit(1).alias("side"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("ut") - 1)).alias("a"), F.pmod(F.xxhash64("node"), F.col("vt")).alias("b"), "node", "raw", "size")
    single = left.unionByName(right).groupBy("u", "v", "a", "b").applyInPandas(kernels.open_tile(cosine, kind), "u string, v string, node string, links long")
    single = materialize(single, "vector-open")

    edges = found.where("kind = 'edge'").select("u", "v").union(single.where("node is null").select("u", "v"))
    roots = components(edges, "vector-roots").select(F.col("node").alias("ball"), "root")
    by_ball = found.where("kind = 'count'").groupBy(F.col("u").alias("ball")).agg(F.sum("links").alias("ball_links"))
    by_node = single.where("node is not null").groupBy("node").agg(F.sum("links").alias("node_links"))
    named = balls.select("ball", "size", "low").join(roots, "ball", "left").join(by_ball, "ball", "left").withColumn("root", F.coalesce("root", "ball"))
    named = named.join(named.groupBy("root").agg(F.min("low").alias("component_id")), "root")
    zero = F.lit(0)
    named = member.join(named, "ball").join(by_node, "node", "left").select("node", "component_id", (F.col("size") - 1 + F.coalesce("ball_links", zero) + F.coalesce("node_links", zero)).alias("n_links"))
    out = ready.select("id", "node").join(materialize(named, "vector-named"), "node", "left")
    component = F.coalesce("component_id", "id")
    return out.select(F.col("id").alias(id_col), F.coalesce("n_links", zero).cast("long").alias("n_links"), component.alias("component_id"), F.col("id").eqNullSafe(component).alias("kept"))
