"""What methods without SQL of their own must fulfil: one row ``(n, holds)`` each.

``n`` counts what the method covered and is told by DuckDB from the tables; ``holds`` is the rule, named in the query's docstring.
"""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corridor.baselines import codecs, relational
from corridor.functions.quant import bit_length
from corridor.operators import families, measures, segquery
from corridor.operators.segment import expand, scan_sql, segment
from corridor.options import Options
from corridor.plans import codec
from corridor.queries.methods import CODEC, D2, F2, REFEREE, W, all_pairs, by_buckets, cte, on, opt
from corridor.queries.registry import add
from corridor.queries.workloads import LAMS, split_row

SAMPLES = "SELECT count(*) AS n, true AS holds FROM track"


def samples(name: str = "f2", select: str = SAMPLES) -> str:
    return f"WITH {cte(name)} {select}"


def pieces(o: Options, name: str = "f2", times: int = 1):
    return lambda: scan_sql(cte(name), o, f"SELECT count(*) * {times} AS n, true AS holds FROM pieces")


def verdict(df: DataFrame, n: Column, rule: Column) -> DataFrame:
    return df.agg(n.cast("long").alias("n"), F.bool_and(F.coalesce(rule, F.lit(False))).alias("holds"))


def near(t: DataFrame, back: DataFrame, limit: float) -> DataFrame:
    """Every sample comes back within the limit."""
    return verdict(t.join(back.withColumnRenamed("x", "back"), ["k", "t"], "left"), F.count("*"), F.abs(F.col("x") - F.col("back")) <= limit * (1 + 1e-9))


def same_rows(a: DataFrame, b: DataFrame) -> DataFrame:
    """Both hold the same rows; counts those of the first."""
    columns = a.columns
    both = a.withColumn("side", F.lit(1)).unionByName(b.withColumn("side", F.lit(-1))).groupBy(*columns).agg(F.sum("side").alias("over"), F.sum((F.col("side") == 1).cast("long")).alias("first"))
    return verdict(both, F.sum("first"), F.col("over") == 0)


def in_order(rows: DataFrame, key: str, value: str, rising: bool) -> DataFrame:
    """The value moves one way with the key, over a handful of rows."""
    ordered = rows.agg(F.array_sort(F.collect_list(F.struct(F.col(key).cast("double").alias("a"), F.col(value).cast("double").alias("b")))).alias("r"), F.count("*").alias("n"))
    steps = F.transform(F.sequence(F.lit(1), F.col("n").cast("int") - 1), lambda i: F.col("r")[i]["b"] - F.col("r")[i - 1]["b"])
    return ordered.select("n", F.forall(steps, (lambda d: d >= 0) if rising else (lambda d: d <= 0)).alias("holds"))


def of(n: int) -> str:
    return f"SELECT CAST({n} AS BIGINT) AS n, true AS holds"


def optimal(t: DataFrame, family: str) -> DataFrame:
    """The greedy search makes as many pieces of a series' block as the best cover has."""
    greedy = families.segment_with(t, family, REFEREE).groupBy("block", "k").agg(F.count("*").alias("found"))
    return verdict(codecs.optimal_pieces(t, REFEREE, family).join(greedy, ["block", "k"], "full"), F.count("*"), F.col("found") == F.col("pieces"))


SERIES = "SELECT count(*) AS n, true AS holds FROM (SELECT DISTINCT k, t // {block} FROM track)"
for fam in ("free_line", "constant"):
    add(f"check_b14_{fam}_f2", on("f2", lambda t, fam=fam: optimal(t, fam)), samples(select=SERIES.format(block=REFEREE.block)))


def within(t: DataFrame, fam: str) -> DataFrame:
    """A family's pieces cover every sample once and stay within the line tolerance of it, by their parameters alone.

    A polynomial's are over its own span mapped to -1..1, a line's over the step within the block.
    """
    o = opt("f2", block=128)
    p = families.segment_with(t, fam, o).select("k", "block", F.col("n").alias("span"), "params", F.col("t0").alias("from"), F.explode(F.sequence(F.col("t0"), F.col("t0") + F.col("n") - 1)).alias("t"))
    u = 2 * (F.col("t") - F.col("from")) / F.greatest(F.lit(1), F.col("span") - 1) - 1 if fam == "poly" else F.col("t") - F.col("block") * o.block
    height = F.aggregate(F.reverse("params"), F.lit(0.0), lambda total, c: total * u + c)
    return verdict(t.join(p, ["k", "t"], "full"), F.count("*"), F.abs(height - F.col("x") / o.grid) <= o.slack + 1e-6)


add("check_m5b_free_line_f2", on("f2", lambda t: within(t, "free_line")), samples())
add("check_m5c_poly_f2", on("f2", lambda t: within(t, "poly")), samples())


def shared_width(t: DataFrame) -> DataFrame:
    """The shared-width code of a chunk takes no more than groups of 64 at the chunk's widest number would."""
    c = measures.vwidth_bits(codec.chunk_numbers(segment(t, W), W).withColumn("widest", F.array_max(F.transform("numbers", bit_length))).withColumn("size", F.size("numbers")))
    return verdict(c, F.sum("n"), F.col("bits") <= F.col("size") * F.col("widest") + 10 * (F.ceil(F.col("size") / 64) + 6))


def buckets_cost(t: DataFrame) -> DataFrame:
    return in_order(by_buckets(t), "buckets", "packed_bits", True)


add("check_m13_codec_f2", on("f2", lambda t: near(t, codec.decompress(codec.compress(t, CODEC), CODEC), CODEC.eps)), samples())
add("check_m13_codec_f5", on("f5", lambda t: near(t, codec.decompress(codec.compress(t, opt("f5")), opt("f5")), opt("f5").eps)), samples("f5"))
add("check_m14_from_store_f2", on("f2", lambda t: same_rows(expand(segment(t, CODEC), None, CODEC), codec.decompress(codec.compress(t, CODEC), CODEC))), samples())
add("check_m20_fused_f2", on("f2", lambda t: near(t, codec.decompress(codec.compress(t, CODEC, fused=False), CODEC), CODEC.eps)), samples())
add("check_m12_shared_width_f2", on("f2", shared_width), pieces(W))
add("check_m19_buckets_f2", on("f2", buckets_cost), of(7))


def bounds(t: DataFrame) -> DataFrame:
    """A pair's least distance at the raw samples is never below the lower bound, and the pieces' own lies within theirs."""
    s = t.select(F.floor(F.col("k") / 2).alias("p"), (F.col("k") % 2).alias("axis"), "t", "x")
    l, r = s.toDF("a", "axis", "t", "xa"), s.toDF("b", "axis", "t", "xb")  # noqa: E741
    d2 = (F.col("xa") - F.col("xb")) * (F.col("xa") - F.col("xb"))
    raw = l.join(r, ["axis", "t"]).where("a < b").groupBy("a", "b", "t").agg(F.sum(d2).alias("d2")).groupBy("a", "b").agg(F.sqrt(F.min("d2")).alias("raw"))
    rule = (F.col("raw") >= F.col("low") - 1e-5) & (F.col("low") <= F.col("continuous") + 1e-5) & (F.col("continuous") <= F.col("high") + 1e-5) & (F.col("continuous") <= F.col("sampled") + 1e-5)
    return verdict(segquery.min_distance(segment(t, D2), all_pairs(t), 2, D2).join(raw, ["a", "b"], "full"), F.count("*"), rule)


def meetings(t: DataFrame) -> DataFrame:
    """A pair has an encounter below a limit exactly if its least distance along the pieces is below it, and no encounter ends before it begins."""
    p = segment(t, D2)
    met = segquery.encounters(p, all_pairs(t), 2, 0.5, D2).groupBy("a", "b").agg(F.bool_and(F.col("s") <= F.col("e")).alias("forward"))
    both = segquery.min_distance(p, all_pairs(t), 2, D2).join(met, ["a", "b"], "left")
    return verdict(both, F.count("*"), F.when(F.abs(F.col("continuous") - 0.5) < 1e-4, True).when(F.col("continuous") < 0.5, F.col("forward")).otherwise(F.col("forward").isNull()))


PAIRS = "SELECT n * (n - 1) // 2 AS n, true AS holds FROM (SELECT count(DISTINCT k // 2) AS n FROM track)"
add("check_m17_bounds_f2", on("f2", bounds), samples(select=PAIRS))
add("check_m17_encounters_f2", on("f2", meetings), samples(select=PAIRS))


def huffman_near_entropy(t: DataFrame) -> DataFrame:
    """A Huffman code takes at least the entropy and less than one bit more a number, escapes aside."""
    p = segment(t, F2)
    least = relational.run(p, relational.entropy(F2)).select("part", "bits_per_number")
    code = codecs.huffman_bits(p).join(least, "part")
    each = F.col("bits") / F.col("n")
    return verdict(code, F.sum("n"), (each >= F.col("bits_per_number") - 1e-5) & (each <= F.col("bits_per_number") + 1))


add("check_m21_huffman_f2", on("f2", huffman_near_entropy), pieces(F2, times=2))

# an adaptive coder on the pieces themselves, and its gain on the shared-width code
add("m21_range_coder_f2", on("f2", lambda t: codecs.piece_coder(segment(t, CODEC), CODEC)))
add("check_m21_range_coder_f2", on("f2", lambda t: verdict(codecs.piece_coder(segment(t, CODEC), CODEC), F.sum("n"), F.col("lossless"))), pieces(CODEC))

# comparison codecs give back every value
add("check_b3_general_f2", on("f2", lambda t: verdict(codecs.general(t, F2), F.sum("raw_bytes") / 24, F.col("lossless"))), samples())
add("check_b6a_native_full_f2", on("f2", lambda t: verdict(codecs.native_full(t, F2), F.sum("raw_bytes") / 8, F.col("lossless"))), samples())
for order in (0, 1):
    add(f"check_b7_range_coder_{order}_f2", on("f2", lambda t, order=order: verdict(codecs.predictive_coder(t, F2, order), F.sum("n"), F.col("lossless"))), samples())
add("check_b11_components_f2", on("f2", lambda t: in_order(codecs.pca(t, [1, 2, 4, 8, 16, 32, 64]), "r", "energy", True)), of(7))
add("check_b12_poly_window_f2", on("f2", lambda t: verdict(codecs.poly_window(t, F2), F.sum("n"), F.col("err") <= F2.eps * (1 + 1e-9))), samples())
add("check_b13_simplify_f2", on("f2", lambda t: verdict(codecs.simplify(t, F2), F.count("*"), F.col("err") <= F2.eps * (1 + 1e-9))), samples(select=SERIES.format(block=F2.block)))
add("b10_fitted_codes_f8", on("f8", lambda t: codecs.fitted_codes(t)))
add("check_b10_fitted_codes_f8", on("f8", lambda t: verdict(codecs.fitted_codes(t), F.sum("n") / 3, F.col("lossless"))), samples("f8"))

# measures and workloads
add("check_a1_ratio_f2", on("f2", lambda t: verdict(measures.metric(t, replace(F2, width=64), dims=2), F.sum("raw_bytes") / 8, F.abs(F.col("ratio") * F.col("packed_bits") / (8 * F.col("raw_bytes")) - 1) < 1e-3)), samples())
add("check_w2_bits_fall_f2", on("f2", lambda t: in_order(reduce(DataFrame.union, [measures.metric(t, replace(F2, eps=e, block=1 << 20, width=64), dims=2).select("eps", "bits_per_sample") for e in (3.0, 1.0, 0.1, 0.01)]), "eps", "bits_per_sample", False)), of(4))


def split_behaviour(t: DataFrame) -> DataFrame:
    """With the split up to one half the size stays within a factor of three of the least; at 1 it is five times the least at least."""
    rows = reduce(DataFrame.union, [split_row(segment(t, replace(F2, lam=lam, block=1 << 20)), lam, "supports") for lam in LAMS])
    least = rows.agg(F.min("bits").alias("least"))
    rule = F.when(F.col("lambda") <= 0.5, F.col("bits") <= 3 * F.col("least")).when(F.col("lambda") == 1, F.col("bits") >= 5 * F.col("least")).otherwise(True)
    return verdict(rows.crossJoin(F.broadcast(least)), F.count("*"), rule)


add("check_w6_split_f2", on("f2", split_behaviour), of(len(LAMS)))
