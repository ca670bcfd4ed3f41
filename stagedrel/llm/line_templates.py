"""Line dedup with a log-template tree (DataFrame functions only).

Every line is parsed to a fixed depth: first by its token count, then by its leading tokens (``depth``, or half of a
shorter line), with variable fields (tokens that hold a digit, addresses) read as ``<*>``. Lines of one tree leaf that
agree in all masked tokens are one template. In a leaf with several kinds of lines the modal token at each position
makes a wider template: positions without a majority become variable fields too, and a line belongs to it if it agrees
on the share ``similarity`` of its tokens. Lines that don't belong go on to a deeper level, dealt by their token at the
position that is shared best, until no template can be left among them. A second tree parses by the last tokens in the
same way, so that a field among the first ones hides no template.

A template that occurs in ``min_docs`` different texts recurs, and its lines are dropped from every document. Equal
texts count once, by content hash, as they are the work of document dedup. For the same reason a document of which no
word would be left stays whole: all of it stands elsewhere, and dropping it everywhere would lose the text altogether.

Defined results: a null or empty text comes back as it is, with no lines dropped; blank lines and lines of which more
than half are variable fields are never dropped; rows with the same id and text get the same result, rows with the
same id and other texts their own; other columns pass through, but for ``n_lines`` and ``n_dropped``, which are
replaced; empty tables give empty results. No key is collected: hot templates and leaves are counted with partial
aggregates, and positions of dropped lines are gathered for each document only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import content_key, materialize, small

#: A whole token that varies between instances of a template; anchored at token starts, so linear in the text.
VARIABLE = r"(?<!\S)(?:[^\s\d]*+\d\S*+|https?://\S*+|[^\s@]++@\S*+)"
FIELD = "<*>"
#: A line without a match of this has no variable field and only single spaces: the common case, left as it is.
WORK = r"[0-9@\t\x0B\f\r]|  |://"
#: A token without digits that holds a letter.
A_WORD = r"(?<!\S)[^\s\d]*\p{L}[^\s\d]*(?!\S)"


def parsed_lines(text: Column, depth: int) -> Column:
    """Array with a struct per line: n (tokens), fields (variable ones), leaf and tail (of the two trees), skeleton (hashes), line (masked tokens, one space between)."""

    def clean(raw: Column) -> Column:
        spaced = F.regexp_replace(F.regexp_replace(raw, VARIABLE, FIELD), r"[ \t\x0B\f\r]+", " ")
        return F.trim(F.when(raw.rlike(WORK), spaced).otherwise(raw))

    def without(line: Column, part: str) -> Column:
        return F.length(line) - F.length(F.replace(line, F.lit(part), F.lit("")))

    def one(line: Column) -> Column:
        n = F.when(line == "", 0).otherwise(without(line, " ") + 1)
        few = F.greatest(F.lit(1), F.least(F.lit(depth), F.shiftright(n, 1)))
        leaf, tail = (F.xxhash64(F.lit(side) * n, F.call_function("substring_index", line, F.lit(" "), side * few)) for side in (1, -1))
        fields = F.when(F.contains(line, F.lit(FIELD)), (without(line, FIELD) / len(FIELD)).cast("int")).otherwise(0)
        return F.struct(n.alias("n"), fields.alias("fields"), leaf.alias("leaf"), tail.alias("tail"), F.xxhash64(line).alias("skeleton"), line.alias("line"))

    return F.transform(F.transform(F.split(F.coalesce(text, F.lit("")), "\n"), clean), one)


def in_texts(rows: DataFrame, key: str, min_docs: int) -> DataFrame:
    """The keys that occur in ``min_docs`` different texts. Keys that can't are left out by one partial aggregate; no key's rows meet in one task."""
    may = rows.groupBy(key).agg(F.count("*").alias("c"), F.min("h1").alias("a"), F.max("h1").alias("b")).where(F.col("c") >= min_docs).where("a <> b" if min_docs > 1 else "true").select(key)
    may = materialize(may, "line-often")
    texts = rows.join(small(may), key, "left_semi").select(key, "h1", "h2").distinct()
    return texts.groupBy(key).count().where(F.col("count") >= min_docs).select(key)


def wider(shapes: DataFrame, min_docs: int, similarity: float) -> DataFrame | None:
    """(template, skeleton, sure, texts): the lines of the leaves' wider templates, found level by level.

    shapes: a row per kind of line: s (leaf), skeleton, line, w (texts, as far as they matter), texts, sure (recurs by itself).
    """
    found = None
    while not shapes.isEmpty():
        at = shapes.select("s", "w", F.posexplode(F.split("line", " ")).alias("p", "token")).groupBy("s", "p", "token").agg(F.sum("w").alias("c"))
        at = at.groupBy("s", "p").agg(F.max(F.struct("c", "token")).alias("top"), F.sum("c").alias("all"), F.count("*").alias("kinds"), F.sum(F.when(F.col("c") >= min_docs, F.col("c")).otherwise(0)).alias("common"))
        at = at.withColumn("token", F.when(F.col("top.c") * 2 > F.col("all"), F.col("top.token")))
        # the next level is dealt by the position whose tokens are shared best
        best = F.max(F.when((F.col("kinds") > 1) & (F.col("common") > 0), F.struct("common", (-F.col("kinds")).alias("few"), (-F.col("p")).alias("p"))))
        plan = at.groupBy("s").agg(F.sort_array(F.collect_list(F.struct("p", "token"))).alias("t"), F.count(F.when(F.col("token") != FIELD, 1)).alias("fixed"), F.count("*").alias("n"), (-best["p"]).alias("by"))
        plan = materialize(plan.select("s", F.col("t.token").alias("template"), (F.col("fixed") >= similarity * F.col("n")).alias("holds"), "n", "by"), "line-plan")
        tokens = F.split("line", " ")
        agree = F.aggregate(F.zip_with(tokens, "template", lambda a, b: F.when(a == b, 1).otherwise(0)), F.lit(0), lambda x, y: x + y)
        dealt = shapes.join(small(plan, "n"), "s").withColumn("member", F.col("holds") & (agree >= similarity * F.col("n")))
        dealt = materialize(dealt.select(F.xxhash64("s", F.lit("rest"), F.get(tokens, F.col("by"))).alias("deeper"), "s", "skeleton", "line", "w", "texts", "sure", "member", "by"), "line-dealt")
        own = dealt.where("member").select(F.col("s").alias("template"), "skeleton", "sure", "texts")
        found = own if found is None else found.union(own)
        rest = dealt.where("not member and by is not null").select(F.col("deeper").alias("s"), "skeleton", "line", "w", "texts", "sure")
        lone = rest.groupBy("s").agg(F.sum("w").alias("c"), F.min("skeleton").alias("a"), F.max("skeleton").alias("b")).where(F.col("c") >= min_docs).where("a <> b").select("s")
        shapes = materialize(rest.join(small(materialize(lone, "line-deeper")), "s", "left_semi"), "line-level")
    return found


def recurring_lines(docs: DataFrame, depth: int = 4, min_docs: int = 3, similarity: float = 0.7, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(did, h1, h2, pos): lines of docs whose template recurs; did, h1 and h2 identify the document."""
    h1, h2 = content_key(F.col(text_col))
    # the outer generator keeps the parse from running again in an inferred filter
    whole = docs.select(F.coalesce(F.col(id_col).cast("string"), F.lit("")).alias("did"), h1.alias("h1"), h2.alias("h2"), parsed_lines(F.col(text_col), depth).alias("lines"))
    lines = whole.select("did", "h1", "h2", F.posexplode_outer("lines").alias("pos", "x")).select("did", "h1", "h2", "pos", "x.n", "x.fields", "x.leaf", "x.tail", "x.skeleton", "x.line")
    lines = materialize(lines.where("n > 0 and 2 * fields <= n").drop("fields"), "line-templates")
    exact = materialize(in_texts(lines, "skeleton", min_docs), "line-recurring")

    # leaves with several kinds of lines, of which some token may vary
    free = lines.where(F.col("n") - F.ceil(F.col("n") * similarity) >= 1).withColumn("leaf", F.explode(F.array("leaf", "tail"))).drop("tail")
    busy = free.groupBy("leaf").agg(F.min("skeleton").alias("a"), F.max("skeleton").alias("b"), F.min("h1").alias("x"), F.max("h1").alias("y"), F.count("*").alias("c")).where("a <> b and x <> y").where(F.col("c") >= min_docs).select("leaf")
    kinds = free.join(small(materialize(busy, "line-busy")), "leaf", "left_semi").join(small(exact).withColumn("sure", F.lit(True)), "skeleton", "left")
    text = F.when(F.col("sure").isNull(), F.struct("h1", "h2"))  # a line that doesn't recur by itself has few texts
    shapes = kinds.groupBy(F.col("leaf").alias("s"), "skeleton").agg(F.first("line").alias("line"), F.collect_set(text).alias("texts"), F.first("sure").isNotNull().alias("sure"))
    found = wider(materialize(shapes.withColumn("w", F.when(F.col("sure"), min_docs).otherwise(F.size("texts"))), "line-shapes"), min_docs, similarity)
    gone = exact
    if found is not None:
        found = materialize(found, "line-members")
        texts = found.select("template", F.explode("texts").alias("x")).distinct().groupBy("template").count().where(F.col("count") >= min_docs).select("template")
        recur = materialize(texts.union(found.where("sure").select("template")).distinct(), "line-wider")
        gone = exact.union(found.join(small(recur), "template", "left_semi").select("skeleton")).distinct()
    gone = small(materialize(gone, "line-gone"))
    return lines.join(gone, "skeleton", "left_semi").select("did", "h1", "h2", "pos")


def drop_recurring_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """docs with recurring lines taken out of the text, and ``n_lines`` and ``n_dropped`` added."""
    gone = recurring_lines(docs, id_col=id_col, text_col=text_col, **how).groupBy("did", "h1", "h2").agg(F.collect_set("pos").alias("__gone"))
    h1, h2 = content_key(F.col(text_col))
    keys = {"__did": F.coalesce(F.col(id_col).cast("string"), F.lit("")), "__h1": h1, "__h2": h2}
    gone = gone.select(F.col("did").alias("__did"), F.col("h1").alias("__h1"), F.col("h2").alias("__h2"), "__gone")
    out = docs.withColumns(keys).join(gone, list(keys), "left")
    split = F.split(text_col, "\n", -1)
    kept = F.array_join(F.filter(split, lambda line, i: ~F.array_contains("__gone", i)), "\n")
    out = out.withColumn("__kept", F.when(F.col("__gone").isNotNull(), kept)).withColumn("__kept", F.when(F.col("__kept").rlike(A_WORD), F.col("__kept")))
    whole = F.col("__kept").isNull()
    result = {text_col: F.when(whole, F.col(text_col)).otherwise(F.col("__kept")), "n_lines": F.when(F.coalesce(F.col(text_col), F.lit("")) == "", 0).otherwise(F.size(split)), "n_dropped": F.when(whole, 0).otherwise(F.size("__gone"))}
    plain = [result[c].alias(c) if c == text_col else F.col(c) for c in docs.columns if c not in ("n_lines", "n_dropped")]
    return out.select(*plain, *[result[c].cast("long").alias(c) for c in ("n_lines", "n_dropped")])
