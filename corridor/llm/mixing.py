"""Mixing sources to target weights: capped water-filling and seeded repetition.

The budget is shared by weight; a source whose share exceeds ``epochs`` times its size is clamped there, and the rest is shared
again among the others until none exceeds.  A source then takes every document a whole number of times, and some of them
once more.  How many is settled from its largest size class to its smallest: each class takes the fraction of its words that
is due, and what a whole number of documents misses or exceeds is carried to the next class.  Which documents of a class
is a matter of the seeded hash.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corridor.llm.texthash import unused
from corridor.runtime import cut

WEIGHTS = (5, 2, 1)
SALTS = 16
WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"


def n_words(text: Column) -> Column:
    """Number of words: white space runs become one space, and spaces between words are counted."""
    flat = F.translate(text.cast("string"), "\t\n\x0b\f\r", "     ")
    return F.coalesce(F.size(F.filter(F.split(flat, " "), lambda w: w != "")), F.lit(0)).cast("long")


def water_fill(sources: DataFrame, share: float, epochs: float) -> DataFrame:
    """``sources(source, weight, size)`` with target; only three numbers of each round reach the driver."""
    total = sources.agg(F.sum("size")).first()[0] or 0
    level, capped = 0.0, -1
    while True:
        over = F.col("weight") * level > epochs * F.col("size")
        n, held, weight = sources.agg(F.count_if(over), F.sum(F.when(over, F.col("size")).otherwise(0)), F.sum(F.when(over, 0).otherwise(F.col("weight")))).first()
        if n == capped or not weight:
            break
        capped, level = n, (share * total - epochs * held) / weight
    return sources.withColumn("target", F.least(F.col("weight") * level, epochs * F.col("size")).cast("double"))


def size_class(size: Column) -> Column:
    """Eight classes for each power of two; sizes below 16 have a class each."""
    bits = F.length(F.bin(size))
    return F.when(size < 16, size).otherwise(bits * 8 + F.floor(size / F.pow(F.lit(2.0), bits - 4)) % 8).cast("int")


def draws(docs: DataFrame, weights: tuple = WEIGHTS, share: float = 1.5, epochs: float = 2.0, seed: str = "mix-1") -> DataFrame:
    """doc_id, source, size, source_size, target and copies of every row of ``docs(doc_id, text, source)``.

    size is the number of words, none for a null text.  Weights repeat along the sources in the order of their code points, null last.
    Documents without words are taken as often as others.  Rows that repeat a doc_id are drawn one after the other; a null doc_id
    is drawn like any.  Copies are whole and never more than ``epochs`` rounded up.  An empty table gives an empty one.
    """
    doc_id = F.col("doc_id").cast("long")
    rows = cut(docs.select(doc_id.alias("doc_id"), F.col("source").cast("string").alias("source"), n_words(F.col("text")).alias("size"), F.md5(F.concat(F.coalesce(doc_id.cast("string"), F.lit("-")), F.lit(f"/{seed}"))).alias("draw")))
    return _drawn(rows, weights, share, epochs)


def _drawn(rows: DataFrame, weights: tuple, share: float, epochs: float) -> DataFrame:
    named = F.struct(F.col("source").isNull().alias("none"), F.coalesce("source", F.lit("")).alias("name")).alias("key")
    rows = rows.withColumn("key", named)
    sources = cut(rows.groupBy("key").agg(F.sum("size").alias("size"), F.count("*").alias("docs")))
    place = F.row_number().over(Window.orderBy("key")) - 1  # a row for each source
    sources = cut(sources.withColumn("weight", F.get(F.array(*map(F.lit, weights)), F.pmod(place, F.lit(len(weights))))))
    filled = water_fill(sources, share, epochs)
    filled = cut(filled.select("key", F.col("size").alias("source_size"), "target", F.when(F.col("size") > 0, F.col("target") / F.col("size")).otherwise(F.lit(0.0)).alias("rate")))
    rows = rows.withColumn("class", size_class(F.col("size"))).withColumn("salt", F.substring("draw", 32, 1))
    cells = cut(rows.groupBy("key", "class", "salt").agg(F.count("*").alias("n"), F.sum("size").alias("words")))
    classes = cells.groupBy("key", "class").agg(F.sum("n").alias("n"), F.sum("words").alias("words"))
    ladder = classes.groupBy("key").agg(F.sort_array(F.collect_list(F.struct("class", "n", "words")), False).alias("ladder"))  # a few hundred classes at most
    ladder = ladder.join(filled, "key")

    def take(acc: Column, step: Column) -> Column:
        part = F.col("rate") - F.floor("rate")
        mean = step["words"] / step["n"]
        due = step["words"] * part + acc["carry"]
        more = F.when(part == 0, F.lit(0.0)).when(mean == 0, F.round(part * step["n"])).otherwise(F.greatest(F.lit(0.0), F.least(F.round(due / mean), step["n"].cast("double"))))
        return F.struct((due - more * mean).alias("carry"), F.concat(acc["taken"], F.array(F.struct(step["class"].alias("class"), more.cast("long").alias("more")))).alias("taken"))

    start = F.struct(F.lit(0.0).alias("carry"), F.expr("cast(array() as array<struct<class:int,more:bigint>>)").alias("taken"))
    taken = ladder.select("key", "source_size", "target", F.floor("rate").alias("whole"), F.explode(F.aggregate("ladder", start, take, lambda acc: acc["taken"])).alias("c")).select("key", "source_size", "target", "whole", "c.*")
    before = F.sum("n").over(Window.partitionBy("key", "class").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1))
    cells = cells.select("key", "class", "salt", F.coalesce(before, F.lit(0)).alias("before")).join(taken, ["key", "class"])
    ranked = rows.withColumn("at", F.row_number().over(Window.partitionBy("key", "class", "salt").orderBy("draw", "doc_id", "size")) - 1)
    joined = ranked.join(cells, ["key", "class", "salt"])
    extra = (F.col("before") + F.col("at") < F.col("more")).cast("long")
    return joined.select("doc_id", "source", "size", "source_size", "target", (F.col("whole") + extra).cast("long").alias("copies"))


BROADCAST_ROWS = 1 << 20


def mixed(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with each row as often as it is drawn; rows that repeat a doc_id share what one of them draws."""
    key, copies, copy = (unused(x, docs) for x in ("__id", "__copies", "__copy"))
    own = cut(draws(docs, **options).groupBy(F.col("doc_id").alias(key)).agg(F.max("copies").alias(copies)))
    own = F.broadcast(own) if own.count() <= BROADCAST_ROWS else own
    taken = docs.join(own, F.col("doc_id").cast("long").eqNullSafe(F.col(key)))
    return taken.withColumn(copy, F.explode(F.expr(f"if({copies} > 0, sequence(1L, {copies}), cast(array() as array<bigint>))"))).drop(key, copies, copy)
