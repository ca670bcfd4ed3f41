"""Benchmark decontamination by template canonicalisation (DataFrame functions only).

Texts become token templates: numbers, units after a number, and names (a capital inside a sentence) are typed
placeholders. Windows of ``width`` tokens are hashed at every position of a benchmark item and of a document, so that
each shared run of ``width`` tokens has a window in the join. A second template leaves names as words, so that
passages in capitals, in lower case or in title case are met too; its windows differ from the first ones' only around
names. An item whose windows are all made of placeholders for the most part is joined by its fullest ones, or, where
even these say too little, by windows of its plain words; an item shorter than a window by all its words.

Where windows meet, item and document are laid side by side at that offset over the item's whole length; the item
counts as leaked if enough of its tokens agree and the placeholders are filled consistently (one document value for
each item value and the reverse), which also catches questions with other numbers or names.

Defined results: null and empty texts match nothing; an item of fewer than ``least`` tokens can't be told from chance
and matches nothing; repeated rows match alike; a null id is matched and reported as null; empty tables give empty
results; other columns play no part.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import content_key, materialize, small

#: Units that are read as a placeholder after a number.
UNITS = ("km", "m", "cm", "mm", "miles", "mile", "feet", "ft", "inches", "kg", "g", "mg", "lb", "pounds", "tons", "litres", "liters", "ml", "hours", "hour", "minutes", "minute", "seconds", "second", "days", "day", "weeks", "week", "months", "month", "years", "year", "dollars", "euros", "cents", "percent", "degrees", "meters", "metres")
#: Placeholders. Tokens that are a name or a unit begin with theirs; all of them, and digits, sort before letters.
NAME, NUMBER, UNIT = "\u0001", "\u0002", "\u0003"


def marked(text: Column, units: Sequence[str] = UNITS) -> Column:
    """Text with decimals in one token, and with marks before names and before units that follow a number."""
    t = F.regexp_replace(F.coalesce(text, F.lit("")), r" (?<=[\p{Ll},;] )(?=\p{Lu}\p{Ll})", " " + NAME)
    figures = F.regexp_replace(t, r"[.,](?<=\d[.,])(?=\d)", "_")
    figures = F.regexp_replace(figures, rf"(\d[^\p{{L}}\p{{N}}]{{1,3}})(?=(?i:{'|'.join(units)})(?![\p{{L}}\p{{N}}_]))", "$1" + UNIT)
    return F.when(t.rlike(r"\d"), figures).otherwise(t)


def split_tokens(marked_text: Column) -> Column:
    """Lower-case tokens of a marked text."""
    return F.array_remove(F.split(F.lower(marked_text), f"[^\\p{{L}}\\p{{N}}_{NAME}{UNIT}]+"), "")


def unmarked(x: Column) -> Column:
    return F.when((x < NUMBER) | x.startswith(UNIT), F.substring(x, 2, 1 << 30)).otherwise(x)


def template(tokens: Column, names: bool = True) -> Column:
    """Placeholders in the place of numbers, of units that follow a number, and of names (or names as plain words)."""

    def one(x: Column) -> Column:
        held = F.when(x.startswith(NAME), F.lit(NAME) if names else F.substring(x, 2, 1 << 30)).when(x.startswith(UNIT), UNIT).otherwise(NUMBER)
        return F.when(x < ":", held).otherwise(x)

    return F.transform(tokens, one)


def window_hash(tokens: Column, at: Column, width: int) -> Column:
    """Hash of the tokens at and behind a place. Written out, so that it runs compiled over exploded places."""
    return F.xxhash64(*[F.get(tokens, at + k) for k in range(width)])


def places(n: Column, width: int) -> Column:
    return F.when(n >= width, F.sequence(F.lit(0), n - width))


def windows(df: DataFrame, width: int, keep: Sequence[str]) -> DataFrame:
    """keep, kind (0: template, 1: names as words), pos and h of all windows; df has raw (tokens) and names (whether there may be names)."""
    n = F.size("raw")
    held = F.array_compact(F.transform("raw", lambda x, i: F.when(x.startswith(NAME), i)))
    around = F.array_distinct(F.flatten(F.transform(held, lambda i: F.sequence(F.greatest(i - (width - 1), F.lit(0)), F.least(i, n - width)))))
    named = F.col("names") & (n >= width)
    at = F.when(named, F.concat(places(n, width), F.transform(around, lambda i: -1 - i))).otherwise(places(n, width))
    t0 = F.transform("raw", lambda x: F.xxhash64(F.when(x < ":", F.when(x.startswith(NAME), NAME).when(x.startswith(UNIT), UNIT).otherwise(NUMBER)).otherwise(x)))
    t1 = F.when(named, F.transform(template(F.col("raw"), names=False), lambda x: F.xxhash64(x)))
    # places are a column before they are exploded, so that the generator compiles and no row of it copies the arrays; outer: else a filter is inferred that makes them again
    spots = df.select(*keep, t0.alias("t0"), t1.alias("t1"), at.alias("at")).select(*keep, "t0", "t1", F.explode_outer("at").alias("at")).where("at is not null")
    kind, pos = (F.col("at") < 0).cast("int"), F.when(F.col("at") < 0, -1 - F.col("at")).otherwise(F.col("at"))
    spots = spots.select(*keep, kind.alias("kind"), pos.alias("pos"), F.when(F.col("at") < 0, F.col("t1")).otherwise(F.col("t0")).alias("t"))
    return spots.select(*keep, "kind", "pos", window_hash(F.col("t"), F.col("pos"), width).alias("h"))


def word_windows(df: DataFrame, width: int, keep: Sequence[str]) -> DataFrame:
    """keep, pos and h of all windows of plain words, numbers among them."""
    words = F.transform("raw", lambda x: F.xxhash64(F.lit(width), unmarked(x)))
    spots = df.select(*keep, words.alias("t"), places(F.size("raw"), width).alias("at")).select(*keep, "t", F.explode_outer("at").alias("pos")).where("pos is not null")
    return spots.select(*keep, "pos", window_hash(F.col("t"), F.col("pos"), width).alias("h"))


def item_windows(items: DataFrame, width: int, min_constants: int, least_constants: int) -> tuple[DataFrame, DataFrame]:
    """(windows that items are met by: item, n_item, item_pos, h; items that no template window can tell from chance)."""
    placeholder = F.array(F.lit(NAME), F.lit(NUMBER), F.lit(UNIT))
    each = windows(items.withColumn("names", F.lit(True)), width, ["item", "n_item", "raw"])
    own = F.when(F.col("kind") == 0, template(F.col("raw"))).otherwise(template(F.col("raw"), names=False))
    plain = F.size(F.filter(F.slice(own, F.col("pos") + 1, width), lambda x: ~F.array_contains(placeholder, x)))
    each = materialize(each.select("item", "n_item", F.col("pos").alias("item_pos"), "h", plain.alias("plain")), "leak-item-windows")
    fullest = each.groupBy(F.col("item").alias("of")).agg(F.max("plain").alias("most"))
    usable = F.col("plain") >= F.least(F.lit(min_constants), F.greatest(F.col("most"), F.lit(least_constants)))
    keys = each.join(fullest, F.col("item").eqNullSafe(F.col("of"))).where(usable).select("item", "n_item", "item_pos", "h").distinct()
    return keys, materialize(fullest.where(F.col("most") < least_constants).select("of"), "leak-bare")


def leaks(docs: DataFrame, benchmark: DataFrame, width: int = 8, min_constants: int = 5, least_constants: int = 3, least: int = 5, coverage: float = 0.5, min_run: int = 20, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """A row per document and leaked item: id, item, n_item and n_match (tokens), coverage, verbatim, and h1, h2, the text's hashes.

    Leaked: slots are consistent and ``coverage`` of the item's tokens agree, or at least ``min_run`` of them.
    Windows with fewer than ``min_constants`` plain tokens don't start a match, unless an item has no others: then those
    with the most do, from ``least_constants`` on, and below that the item is met by its words, numbers included.
    """
    items = benchmark.select(F.col(item_col).alias("item"), split_tokens(marked(F.col(item_text))).alias("raw")).withColumn("n_item", F.size("raw"))
    items = materialize(items.where(F.col("n_item") >= least), "leak-items")
    placeholder = F.array(F.lit(NAME), F.lit(NUMBER), F.lit(UNIT))
    keys, bare = item_windows(items.where(F.col("n_item") >= width), width, min_constants, least_constants)
    by_words = items.join(bare, F.col("item").eqNullSafe(F.col("of")), "left_semi") if not bare.isEmpty() else items.limit(0)
    by_words = by_words.withColumn("w", F.lit(width)).union(items.where(F.col("n_item") < width).withColumn("w", F.col("n_item")))
    by_words = materialize(by_words, "leak-by-words")
    widths = sorted(r["w"] for r in by_words.select("w").distinct().collect())  # from least to width
    for w in widths:
        keys = keys.union(word_windows(by_words.where(F.col("w") == w), w, ["item", "n_item"]).select("item", "n_item", F.col("pos").alias("item_pos"), "h").distinct())
    keys = materialize(keys, "leak-windows")

    h1, h2 = content_key(F.col(text_col))
    doc = docs.select(F.col(id_col).alias("id"), h1.alias("h1"), h2.alias("h2"), marked(F.col(text_col)).alias("t"))
    doc = doc.select("id", "h1", "h2", split_tokens(F.col("t")).alias("raw"), F.contains("t", F.lit(NAME)).alias("names"))
    spots = windows(doc, width, ["id", "h1", "h2"]).drop("kind")
    for w in widths:
        spots = spots.union(word_windows(doc, w, ["id", "h1", "h2"]))
    met = spots.join(small(keys), "h").groupBy("id", "h1", "h2", "item", "n_item", (F.col("pos") - F.col("item_pos")).alias("shift")).agg(F.count("*").alias("hits"))
    met = materialize(met, "leak-candidates")

    # side by side over the item's length, for the documents that met an item; only that stretch of a text goes on
    k, shift, low = F.col("k"), F.col("shift"), F.least(F.col("shift"), F.lit(0))
    text = _texts_of(docs, met.select("id", "h1", "h2").distinct(), id_col, text_col)
    text = text.select("doc", "t1", "t2", split_tokens(marked(F.col("whole"))).alias("tokens"))
    pairs = met.join(text, met.id.eqNullSafe(text.doc) & (met.h1 == text.t1) & (met.h2 == text.t2))
    stretch = F.slice("tokens", F.greatest(shift, F.lit(0)) + 1, F.col("n_item") + low)
    pairs = pairs.select("id", "h1", "h2", F.col("item").alias("of"), low.alias("low"), stretch.alias("own"))
    pairs = pairs.join(small(items, "n_item"), F.col("item").eqNullSafe(F.col("of"))).withColumns({"tpl": template(F.col("own")), "word_tpl": template(F.col("own"), names=False), "item_tpl": template(F.col("raw")), "item_word": template(F.col("raw"), names=False)})

    def agrees(i: Column) -> Column:
        at = i + F.col("low")
        return (F.get("tpl", at) == F.get("item_tpl", i)) | (F.get("word_tpl", at) == F.get("item_word", i))

    pairs = pairs.withColumn("k", F.array_compact(F.transform(F.sequence(F.lit(0), F.size("item_tpl") - 1), lambda i: F.when(agrees(i), i))))
    slots = F.filter(k, lambda i: F.array_contains(placeholder, F.get("item_tpl", i)))
    ours, theirs = (F.transform(slots, lambda i: unmarked(F.get("raw", i))), F.transform(slots, lambda i: unmarked(F.get("own", i + F.col("low")))))
    both = F.size(F.array_distinct(F.zip_with(ours, theirs, lambda a, b: F.struct(a.alias("a"), b.alias("b")))))
    pairs = pairs.select(
        "id", "h1", "h2", "item", "n_item", F.size("k").alias("n_match"),
        ((both == F.size(F.array_distinct(ours))) & (both == F.size(F.array_distinct(theirs)))).alias("consistent"),
        F.forall(F.zip_with(ours, theirs, lambda a, b: a == b), lambda x: x).alias("verbatim"),
    )
    pairs = pairs.where("consistent").where((F.col("n_match") >= coverage * F.col("n_item")) | (F.col("n_match") >= min_run))
    best = pairs.groupBy("id", "h1", "h2", "item").agg(F.max(F.struct("n_match", "verbatim", "n_item")).alias("b"))
    return best.select(F.col("id").alias(id_col), "h1", "h2", F.col("item").alias(item_col), F.col("b.n_item").alias("n_item"), F.col("b.n_match").alias("n_match"), F.round(F.col("b.n_match") / F.col("b.n_item"), 6).alias("coverage"), F.col("b.verbatim").alias("verbatim"))


def _texts_of(docs: DataFrame, wanted: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """The distinct texts that are wanted."""
    h1, h2 = content_key(F.col(text_col))
    text = docs.select(F.col(id_col).alias("doc"), h1.alias("t1"), h2.alias("t2"), F.col(text_col).alias("whole"))
    text = text.join(wanted, text.doc.eqNullSafe(wanted.id) & (text.t1 == wanted.h1) & (text.t2 == wanted.h2), "left_semi")
    return text.groupBy("doc", "t1", "t2").agg(F.first("whole").alias("whole"))


def without_leaks(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """docs without the rows that leak a benchmark item."""
    bad = leaks(docs, benchmark, id_col=id_col, text_col=text_col, **how).select(F.col(id_col).alias("__id"), F.col("h1").alias("__h1"), F.col("h2").alias("__h2")).distinct()
    h1, h2 = content_key(F.col(text_col))
    return docs.join(bad, docs[id_col].eqNullSafe(F.col("__id")) & (h1 == F.col("__h1")) & (h2 == F.col("__h2")), "left_anti")
