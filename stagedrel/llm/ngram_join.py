"""N-gram Jaccard join by MinHash banding.

A text's set holds the hashes of all its runs of ``size`` words (of a shorter text: of all its words). Texts with equal
sets are one class from the start, with a count of copies. Band and row counts follow from the target recall at the
threshold: as many rows as ``hashes`` allow, for the fewest chance meetings. The shuffle is on band hashes.

Classes that meet in a band are tied into candidate groups, and pairs are verified on their full sets, tile against
tile, in tasks that hold two tiles at most. A group of up to as many tiles as there are bands is verified as a whole,
which moves no text more often than its bands would; a larger one (copies by the thousand, or unlike texts that chance
meetings have tied together) falls apart into its bands, and a pair is verified in the first band that it shares.
A pair is counted and connected where it is found and never becomes a row, so groups of thousands make no rows by
the square, and no link between different texts that share a band is lost.

Defined results: null, empty and wordless texts have no set and link with nothing; repeated rows are copies of each
other; a class is named by its smallest doc_id, null ids come last; other columns play no part; an empty table gives an
empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels
from .common import components, content_key, materialize


def bands_and_rows(similarity: float, recall: float, hashes: int = 288) -> tuple[int, int]:
    """The most rows a band, and as many bands, with which a pair at the threshold meets with the target recall within the hashes."""
    best = None
    for rows in range(1, hashes + 1):
        bands = math.ceil(math.log(1 - recall) / math.log(1 - similarity**rows)) if similarity < 1 else 1
        if bands * rows > hashes:
            break
        best = bands, rows
    if best is None:
        raise ValueError("the recall needs more hashes")
    return best


def jaccard_links(docs: DataFrame, size: int = 5, similarity: float = 0.8, recall: float = 0.998, hashes: int = 288, tile: int = 96, tile_shingles: int = 500_000, seed: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row per row of docs: id, h1, h2 (the text's hashes), set, n_links (other rows linked), class_id (smallest id reachable), root (the class's own key)."""
    h1, h2 = content_key(F.col(text_col))
    bands, rows = bands_and_rows(similarity, recall, hashes)
    # equal texts are read once: a text's key stands for it from here on
    source = docs.select(F.col(id_col).alias("doc"), h1.alias("h1"), h2.alias("h2"), F.col(text_col).alias("text"))
    packed = source.select(F.struct("doc", "h1", "h2").alias("id"), "text")
    schema = f"id struct<doc:{docs.schema[id_col].dataType.simpleString()},h1:bigint,h2:bigint>, n int, `set` string, bands array<long>"
    signed = materialize(packed.mapInPandas(kernels.signature_rows(size, bands, rows, seed), schema).select("id.*", "n", "set", "bands"), "ngram-signatures")
    filled = signed.where("n > 0")
    classes = filled.groupBy("set").agg(F.count("*").alias("copies"), F.min("n").alias("n"), F.min("doc").alias("low"), F.min(F.struct("h1", "h2")).alias("text_key"), F.first("bands").alias("bands"))
    # a class gets a number when it is written, unique and as short as ids can be
    classes = materialize(classes.withColumn("cid", F.monotonically_increasing_id()), "ngram-classes")

    spots = classes.select("cid", F.explode("bands").alias("h"))
    shared = spots.groupBy("h").agg(F.min("cid").alias("v"), F.max("cid").alias("high")).where("v <> high").select("h", "v")
    stars = spots.join(shared, "h").where("cid <> v").select(F.col("cid").alias("u"), "v").distinct()
    groups = components(stars, "ngram-groups").select(F.col("node").alias("cid"), F.col("root").alias("grp"))
    slim = classes.select("cid", "copies", "n", "text_key.h1", "text_key.h2", "bands")
    # a tile holds about ``tile`` texts, or fewer long ones
    tiles = F.ceil(F.greatest(F.count("*") / F.lit(tile), F.sum("n") / F.lit(tile_shingles))).cast("int").alias("tiles")
    part = F.pmod(F.xxhash64("cid"), F.col("tiles")).cast("int").alias("tile")
    groups = groups.join(slim, "cid")
    groups = materialize(groups.join(groups.groupBy("grp").agg(tiles), "grp"), "ngram-groups")
    wide = groups.where(F.col("tiles") > bands)
    members = groups.where(F.col("tiles") <= bands).select("cid", F.array(F.struct(F.lit(True).alias("whole"), F.col("grp").alias("g"), "tiles", part)).alias("at"), F.lit(None).cast("array<bigint>").alias("bands"))
    if not wide.isEmpty():
        met = materialize(wide.select("cid", "n", F.explode("bands").alias("g")), "ngram-bands")
        hot = met.groupBy("g").agg(tiles, F.count("*").alias("texts")).where("texts > 1").drop("texts")
        own = met.join(hot, "g").groupBy("cid").agg(F.collect_list(F.struct(F.lit(False).alias("whole"), "g", "tiles", part)).alias("at"))  # a text's bands at most
        members = members.unionByName(own.join(wide.select("cid", "bands"), "cid"))
    members = materialize(members.join(slim.drop("bands"), "cid"), "ngram-members")

    texts = docs.select(h1.alias("h1"), h2.alias("h2"), F.col(text_col).alias("text"))
    # candidates grow with the corpus: the join is by a shuffle at every size
    texts = texts.join(members.select("h1", "h2").hint("merge"), ["h1", "h2"], "left_semi").groupBy("h1", "h2").agg(F.first("text").alias("text"))
    texts = texts.join(members, ["h1", "h2"]).select("at", "cid", "copies", "n", "bands", "text")
    texts = texts.mapInArrow(kernels.shingle_rows(size), "at array<struct<whole:boolean,g:bigint,tiles:int,tile:int>>, cid long, copies long, n int, bands array<long>, shingles binary")
    texts = texts.select("cid", "copies", "n", "bands", "shingles", F.explode("at").alias("at")).select("cid", "copies", "n", "bands", "shingles", "at.*")
    other = F.explode(F.sequence(F.lit(0), F.col("tiles") - 1))
    paired = texts.withColumn("o", other).withColumns({"a": F.least("tile", "o"), "b": F.greatest("tile", "o")}).drop("o", "tiles")
    checked = materialize(paired.groupBy("whole", "g", "a", "b").applyInPandas(kernels.tile_verifier(similarity), "u long, v long, links long"), "ngram-links")

    roots = components(checked.where("v is not null").select("u", "v"), "ngram-classes").select(F.col("node").alias("cid"), "root")
    links = checked.where("v is null").groupBy(F.col("u").alias("cid")).agg(F.sum("links").alias("links"))
    named = classes.select("set", "cid", "copies", "low").join(roots, "cid", "left").join(links, "cid", "left").withColumn("root", F.coalesce("root", "cid"))
    low = named.groupBy("root").agg(F.min("low").alias("class_id"))
    named = named.join(low, "root").select("set", "root", "class_id", (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"))
    out = signed.select("doc", "h1", "h2", "set").join(materialize(named, "ngram-named"), "set", "left")
    return out.select(F.col("doc").alias(id_col), "h1", "h2", "set", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("class_id", "doc").alias("class_id"), "root")


def one_of_each_class(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """docs with one row of each class: that with the smallest id (of rows with that id in the class, one; null ids come last).

    A class is told by its own key: classes whose smallest ids are equal or null stay apart. Rows without a set stay, each of them.
    """
    linked = jaccard_links(docs, id_col=id_col, text_col=text_col, **how)
    h1, h2 = content_key(F.col(text_col))
    first = F.min(F.struct(F.col(id_col).isNull().alias("last"), F.col(id_col).alias("id"), "h1", "h2"))
    named = linked.where("set <> ''").groupBy("root").agg(first.alias("k"))
    keep = named.select(F.col("k.id").alias("__id"), "k.h1", "k.h2").union(linked.where("set = ''").select(F.col(id_col), "h1", "h2")).distinct()
    keep = keep.select("__id", F.col("h1").alias("__h1"), F.col("h2").alias("__h2"))
    kept = docs.join(keep, docs[id_col].eqNullSafe(F.col("__id")) & (h1 == F.col("__h1")) & (h2 == F.col("__h2")), "left_semi")
    # rows that repeat id and text: only they pass through a shuffle of texts
    twice = materialize(linked.where("set <> ''").groupBy(id_col, "h1", "h2").count().where("count > 1").select(F.col(id_col).alias("__id"), F.col("h1").alias("__h1"), F.col("h2").alias("__h2")), "ngram-repeats")
    if twice.isEmpty():
        return kept
    again = kept[id_col].eqNullSafe(F.col("__id")) & (h1 == F.col("__h1")) & (h2 == F.col("__h2"))
    return kept.join(twice, again, "left_anti").unionByName(kept.join(twice, again, "left_semi").dropDuplicates([id_col, text_col]))
