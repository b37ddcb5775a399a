"""Benchmark decontamination by template canonicalisation, in DataFrame functions only.

Words are lower-cased and stripped of punctuation; numbers (in digits or spelled out), units and names (capitalised
words but for common ones, wherever in a sentence, so that a name reads the same at its start) become typed
placeholders.
Windows of five such words are hash-joined to the windows of all benchmark items; an item of fewer words is one
window of its own length. Windows of placeholders alone, which any table of figures has, find no items but
those that have no others. Where enough of an item's windows occur in a document, the words behind the placeholders
are compared along the best alignment: a leaked question may have other numbers and names than the
item, but one value of the item must then have become one value in the document.

The windows of the benchmark are broadcast only while their number is small; windows of documents
are shuffled only beyond that, and what meets an item is counted per document and item, so a
passage that is in very many documents makes no large group.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import broadcast_if_small, pick, stored, table

WINDOW = 5
#: Share of an item's windows that a document must have.
LEAST_SHARE = 0.5
#: Share of placeholder positions that may disagree with the mapping of values.
MOST_DISAGREEING = 0.25
#: Words taken as units, after lower-casing.
UNITS = "mm cm m km mi ft in mg g kg lb lbs oz ml l gal ms s sec min h hr hrs hour hours minute minutes second seconds day days week weeks month months year years mph kmh kph hz khz mhz ghz kb mb gb tb w kw v a j kj cal kcal usd eur gbp dollar dollars euro euros cent cents percent % $ € £ °c °f".split()


#: Numbers spelled out.
NUMBERS = "two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen nineteen twenty thirty forty fifty sixty seventy eighty ninety hundred thousand million".split()

#: Words that are no names where a sentence begins with them.
COMMON = "a an the this that these those it he she we they you i if when while where who what which why how is are was were do does did has have had can could will would there then thus so and or but for from in on at by to of as with after before each every some all both no not find let given suppose der die das ein eine wenn wie was wer wo und in im le la les un une des si il elle on dans que qui où comment el los las una si como qué quién dónde en y".split()


def words(text: Column) -> Column:
    """Words between white space; none for null."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), r"\s+"), lambda w: w != "")


def templated(w: Column) -> Column:
    """The canonical words: as many as there are words."""

    def canonical(word: Column) -> Column:
        bare = F.regexp_replace(word, r"^[^\p{L}\p{N}%$€£°]+|[^\p{L}\p{N}%$€£°]+$", "")
        low = F.lower(bare)
        listed = lambda x: F.when(x.isin(UNITS), F.lit("#u")).when(x.isin(NUMBERS), F.lit("#n"))
        return (
            F.when(word.rlike(r"^\p{Ll}+$"), F.coalesce(listed(word), word))
            .when(bare == "", word)
            .when(bare.rlike(r"^[$€£]?[0-9][0-9.,:/\-]*$"), F.lit("#n"))
            .when(bare.rlike(r"^[$€£]?[0-9][0-9.,]*(?:\p{L}{1,3}|%|°\p{L})$"), F.lit("#n#u"))
            .when(low.isin(UNITS) | low.isin(NUMBERS), listed(low))
            .when(bare.rlike(r"^\p{Lu}[\p{L}'’\-]*\p{Ll}[\p{L}'’]*$") & ~low.isin(COMMON), F.lit("#p"))
            .otherwise(low)
        )

    return F.transform(w, canonical)


def window_hashes(t: Column, size: int = WINDOW) -> Column:
    """Hashes of all windows of a number of words, by place; null for fewer words than that."""
    n = F.size(t) - (size - 1)
    return F.when(n > 0, F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.xxhash64(F.array_join(F.slice(t, i, size), " "))))


def leaked_items(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text", share: float = LEAST_SHARE) -> DataFrame:
    """A row for each document and benchmark item leaked into it: key, item, n_windows, n_found, kind.

    kind is ``verbatim`` if all words behind placeholders are the item's, else ``reparameterised``.
    An item of fewer than five words is leaked where all of them occur in a row. Documents and items with null keys,
    and items without words, match nothing. Rows that repeat a key
    count as one document; each of its texts can match. Copies of a document are reported each. Extra
    columns are ignored; empty tables give an empty result.
    """
    items = pick(benchmark, item, item_text).toDF("item", "text").filter("item is not null").withColumn("w", words(F.col("text"))).filter("size(w) > 0")
    items = items.withColumn("t", templated(F.col("w"))).withColumn("width", F.least(F.size("w"), F.lit(WINDOW)))
    shorter = F.coalesce(*(F.when(F.col("width") == k, window_hashes(F.col("t"), k)) for k in range(1, WINDOW + 1)))
    items = stored(items.select("item", "w", "t", "width", shorter.alias("h")), "items")
    plain = lambda p: F.exists(F.slice("t", p + 1, WINDOW), lambda x: ~x.startswith("#"))
    places = F.sequence(F.lit(0), F.size("h") - 1)
    some = F.filter(places, plain)
    used = items.withColumn("ps", F.when(F.size(some) > 0, some).otherwise(places))
    known = used.select("item", "width", F.size("ps").alias("of"), F.explode(F.transform("ps", lambda p: F.struct(p.alias("p"), F.get(F.col("h"), p).alias("hash")))).alias("x")).select("item", "width", "of", "x.p", "x.hash")
    widths = sorted(r["width"] for r in items.select("width").distinct().collect())  # WINDOW at most

    rows = pick(docs, key, text).toDF("key", "text").filter("key is not null")
    found = rows.select("key", words(F.col("text")).alias("w")).select("key", templated(F.col("w")).alias("t"))
    # outer: else the optimizer would test the arrays' sizes below, and evaluate all of the above again inside itself
    if len(widths) <= 1:
        found = found.select("key", F.lit((widths or [WINDOW])[0]).alias("width"), window_hashes(F.col("t"), (widths or [WINDOW])[0]).alias("h"))
    else:
        each = F.array(*(F.struct(F.lit(k).alias("width"), window_hashes(F.col("t"), k).alias("h")) for k in widths))
        found = found.select("key", F.explode_outer(each).alias("one")).select("key", "one.width", "one.h")
    places = found.select("key", "width", F.posexplode_outer("h").alias("q", "hash"))
    hits = stored(places.join(broadcast_if_small(known, 40), ["hash", "width"]).select("key", "item", "of", "p", "q"), "hits")

    # places p and q of one alignment differ by the same number
    lines = hits.groupBy("key", "item", "of", (F.col("q") - F.col("p")).alias("shift")).agg(F.collect_set("p").alias("ps"))
    lines = lines.groupBy("key", "item", "of").agg(F.array_distinct(F.flatten(F.collect_list("ps"))).alias("all"), F.max(F.struct(F.size("ps").alias("n"), (-F.col("shift")).alias("back"), "ps")).alias("best"))
    near = lines.select("key", "item", F.col("of").alias("n_windows"), F.size("all").alias("n_found"), (-F.col("best.back")).alias("shift"), F.col("best.ps").alias("ps"))
    near = stored(near.filter(F.col("n_found") >= share * F.col("n_windows")), "near")

    # the words behind the placeholders, in the few documents that are left
    few = near.join(items.select("item", F.col("w").alias("iw"), "t", "width"), "item")
    at = F.array_distinct(F.flatten(F.transform("ps", lambda p: F.sequence(p, p + F.col("width") - 1))))
    slots = F.filter(at, lambda i: F.get(F.col("t"), i).startswith("#"))
    few = few.select("key", "item", "n_windows", "n_found", "shift", "iw", F.col("t").alias("it"), at.alias("at"), slots.alias("slots"))
    full = rows.join(broadcast_if_small(few, 2000), "key").withColumn("w", words(F.col("text"))).drop("text")
    full = stored(full.withColumn("dt", templated(F.col("w"))), "near-words")  # stored, so that the lambdas below do not evaluate it for each place
    strip = lambda x: F.lower(F.regexp_replace(x, r"^[^\p{L}\p{N}]+|[^\p{L}\p{N}]+$", ""))
    pairs = F.transform("slots", lambda i: F.struct(strip(F.get(F.col("iw"), i)).alias("a"), strip(F.get(F.col("w"), (i + F.col("shift")).cast("int"))).alias("b")))
    # equal hashes are taken for equal words no longer: all words of the windows are compared
    full = full.filter(F.forall("at", lambda i: F.get(F.col("it"), i) == F.get(F.col("dt"), (i + F.col("shift")).cast("int"))))
    full = stored(full.select("key", "item", "n_windows", "n_found", pairs.alias("pairs")), "slots")
    disagree = F.size(F.array_distinct("pairs")) - F.size(F.array_distinct(F.transform("pairs", lambda x: x["a"])))
    same = ~F.exists("pairs", lambda x: F.coalesce(x["a"] != x["b"], F.lit(True)))
    judged = full.filter(disagree <= MOST_DISAGREEING * F.size("pairs")).select(
        F.col("key").alias(key), F.col("item").alias(item), "n_windows", "n_found", F.when(same, "verbatim").otherwise("reparameterised").alias("kind")
    )
    return judged.distinct()


def op3_template_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaked_items(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
