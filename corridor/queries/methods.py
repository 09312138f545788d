"""One query or more for each method, baseline and measure."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corridor.baselines import codecs, relational
from corridor.functions import quant
from corridor.operators import families, measures, segquery
from corridor.operators.segment import expand, failed_dims, fold_scan, key_frames, scan_sql, segment, vector_scan
from corridor.options import Options
from corridor.plans import codec
from corridor.plans.advise import advise
from corridor.queries.registry import add
from corridor.runtime import table
from corridor.sources import tracks as T

# track name: (builder, oracle's CTE, options that suit it)
F2 = Options(eps=1.0, block=256)
TRACKS = {
    "f1": ("embed_raw", 64, Options(eps=0.1, block=256)),
    "f2": ("embed_walk", 64, F2),
    "f3": ("event_walk", 0, Options(eps=10.0, block=64)),
    "f4": ("event_hourly", 0, Options(eps=10.0, block=256)),
    "f5": ("supplier_daily", 0, Options(eps=50.0, block=256)),
    "f6": ("nation_daily", 0, Options(eps=1e5, block=256)),
    "f7": ("part_price", 0, Options(eps=100.0, block=64)),
    "f8": ("doc_lengths", 0, Options(eps=100.0, block=256)),
}


def track(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    builder, dims, _ = TRACKS[name]
    return getattr(T, builder)(spark, sf_dir, *([dims] if dims else []))


def cte(name: str) -> str:
    builder, dims, _ = TRACKS[name]
    return T.track_sql(builder, dims or 64)


def opt(name: str, **changes) -> Options:
    from dataclasses import replace

    return replace(TRACKS[name][2], **changes)


def on(name: str, f):
    """A query that applies f to a named track."""
    return lambda spark, sf_dir: f(track(spark, sf_dir, name))


# expressions
for step in ("2eq", "eq", "eq/2"):
    o = opt("f2", step=step)
    add(f"m1_grid_{step.replace('/', '_')}_f2", on("f2", lambda t, o=o: t.select("k", "t", quant.quantize(F.col("x"), o.grid).alias("q"), F.round(quant.dequantize(quant.quantize(F.col("x"), o.grid), o.grid), 6).alias("back"))),
        f"WITH {cte('f2')} SELECT k, t, CAST(floor(x / {o.grid!r} + 0.5) AS BIGINT) AS q, round(CAST(floor(x / {o.grid!r} + 0.5) AS BIGINT) * {o.grid!r}::DOUBLE, 6) AS back FROM track")


def split_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each event's value as a tolerance, shared by one of twelve splits."""
    lams = F.array(*[F.lit(x) for x in LAMS])
    e = table(spark, sf_dir, "events").where("value > 0").select("event_id", "value", lams[(F.col("event_id") % len(LAMS)).cast("int")].alias("lambda"))
    eq, ef = quant.split_budget(F.col("value"), F.col("lambda"))
    return e.select("event_id", "lambda", F.round(eq, 9).alias("eq"), F.round(ef, 9).alias("ef"))


LAMS = (0.01, 0.05, 0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9, 1.0)
add("m2_tolerance_split", split_table, f"SELECT event_id, l AS lambda, round(l * value, 9) AS eq, round((1 - l) * value, 9) AS ef FROM (SELECT event_id, value, CAST({list(LAMS)}[event_id % {len(LAMS)} + 1] AS DOUBLE) AS l FROM events WHERE value > 0)")


def cones(t: DataFrame) -> DataFrame:
    from pyspark.sql import Window

    w = Window.partitionBy("k").orderBy("t")
    rows = t.select("k", "t", (F.lead("x", 1).over(w) - F.col("x")).alias("d1"), (F.lead("x", 2).over(w) - F.col("x")).alias("d2")).where("d2 IS NOT NULL")
    c = quant.meet(quant.cone(F.col("d1"), F.lit(1.0), 0.05), quant.cone(F.col("d2"), F.lit(2.0), 0.05))
    return rows.withColumn("c", c).select("k", "t", F.round("c.lo", 8).alias("lo"), F.round("c.hi", 8).alias("hi"), quant.is_empty(F.col("c")).alias("none"))


add("m3_cones_f2", on("f2", cones), f"""WITH {cte('f2')}, d AS (SELECT k, t, lead(x, 1) OVER w - x AS d1, lead(x, 2) OVER w - x AS d2 FROM track WINDOW w AS (PARTITION BY k ORDER BY t)),
c AS (SELECT k, t, greatest((d1 - 0.05::DOUBLE) / 1.0::DOUBLE, (d2 - 0.05::DOUBLE) / 2.0::DOUBLE) AS lo, least((d1 + 0.05::DOUBLE) / 1.0::DOUBLE, (d2 + 0.05::DOUBLE) / 2.0::DOUBLE) AS hi FROM d WHERE d2 IS NOT NULL)
SELECT k, t, round(lo, 8) AS lo, round(hi, 8) AS hi, lo > hi AS "none" FROM c""")  # fmt: skip

MIXED = "o_orderkey * 7919 % 10001 - 5000"  # orders' keys dealt over both signs
for kind in ("dense", "sparse"):
    add(f"m11_zigzag_{kind}", lambda spark, d, kind=kind: table(spark, d, "orders").select("o_orderkey", F.expr(MIXED).alias("i")).select("o_orderkey", "i", quant.zigzag(F.col("i"), kind).alias("u"), quant.unzigzag(quant.zigzag(F.col("i"), kind), kind).alias("back")),
        f"SELECT o_orderkey, i, CASE WHEN i >= 0 THEN 2 * i ELSE -2 * i {'+ 1' if kind == 'sparse' else '- 1'} END AS u, i AS back FROM (SELECT o_orderkey, {MIXED} AS i FROM orders)")

# M4: segmentation on every track, then every variant on the smooth one
for name in TRACKS:
    if name == "f5":
        continue  # long calendar: with the workloads
    add(f"m4_segment_{name}", on(name, lambda t, o=opt(name): vector_scan(t, o)), lambda name=name: scan_sql(cte(name), opt(name)))
add("m4_segment_fold_f2", on("f2", lambda t: fold_scan(t, F2)), lambda: scan_sql(cte("f2"), F2))
add("m4_segment_fold_f7", on("f7", lambda t: fold_scan(t, opt("f7"))), lambda: scan_sql(cte("f7"), opt("f7")))
VARIANTS = {
    "m4a_inputs": {"mode": "inputs"}, "m4a_inputs_eq": {"mode": "inputs", "step": "eq"}, "m4a_inputs_half": {"mode": "inputs", "step": "eq/2"}, "m4c_feasible": {"mode": "feasible"}, "m4d_disjoint": {"connect": False},
    "m4d_disjoint_feasible": {"connect": False, "mode": "feasible"}, "m4e_end_mid": {"end": "mid"}, "m4e_end_low": {"end": "low"}, "m4e_end_high": {"end": "high"},
    "b15_extrapolation_only": {"lam": 1.0}, "b15_line_only": {"lam": 0.01},
}
for name, change in VARIANTS.items():
    o = opt("f2", **change)
    add(f"{name}_f2", on("f2", lambda t, o=o: segment(t, o)), lambda o=o: scan_sql(cte("f2"), o))
add("m6_division_free_f2", on("f2", lambda t: segment(t, opt("f2", test="cross"))), lambda: scan_sql(cte("f2"), F2))
add("m6_division_free_f3", on("f3", lambda t: segment(t, opt("f3", test="cross", mode="inputs"))), lambda: scan_sql(cte("f3"), opt("f3", mode="inputs")))
add("m6a_failed_tests_f2", on("f2", lambda t: failed_dims(t, F2)), lambda: scan_sql(cte("f2"), F2, "SELECT block, k, t0 + dt + 1 AS t FROM pieces p WHERE t0 + dt < (SELECT z FROM ends e WHERE e.k = p.k AND e.block = p.block)"))

# M5: other families
add("m5a_constant_f2", on("f2", lambda t: families.segment_with(t, "constant", F2).select("block", "k", "t0", "n")), lambda: families.constant_sql(cte("f2"), F2))
for fam in ("free_line", "poly"):
    add(f"m5_{fam}_f2", on("f2", lambda t, fam=fam: families.segment_with(t, fam, opt("f2", block=128))))

# Key frames, wire order, chunks
add("m7_key_frames_f2", on("f2", lambda t: key_frames(t, F2)), f"WITH {cte('f2')}, s AS (SELECT k, t // {F2.block} AS block, t, x FROM track) SELECT block, k, min(t) AS t, CAST(floor(arg_min(x, t) / {F2.grid!r} + 0.5) AS BIGINT) AS q FROM s GROUP BY block, k")
add("m8_blocks_f2", on("f2", lambda t: t.groupBy(F.floor(F.col("t") / F2.block).alias("block")).agg(F.count("*").alias("samples"), F.min("t").alias("first"), F.max("t").alias("last"))),
    f"WITH {cte('f2')} SELECT t // {F2.block} AS block, count(*) AS samples, min(t) AS \"first\", max(t) AS \"last\" FROM track GROUP BY 1")
W = opt("f2", chunk=64, width=8)
ORDERED = f"(row_number() OVER (PARTITION BY block, k // {W.width} ORDER BY t0, k) - 1)"
add("m9_wire_order_f2", on("f2", lambda t: codec.wire_order(segment(t, W), W).select("block", "bucket", "k", "t0", "place", "seq")),
    lambda: scan_sql(cte("f2"), W, f"SELECT block, CAST(k // {W.width} AS INTEGER) AS bucket, k, t0, CAST({ORDERED} AS INTEGER) AS place, CAST({ORDERED} // {W.chunk} AS INTEGER) AS seq FROM pieces"))
add("m9a_explicit_ids_f2", on("f2", lambda t: segment(t, W).agg(F.count("*").alias("pieces"), (F.count("*") * quant.bit_length(F.max("k"))).cast("long").alias("id_bits"))),
    lambda: scan_sql(cte("f2"), W, "SELECT count(*) AS pieces, CAST(count(*) * length(bin(max(k))) AS BIGINT) AS id_bits FROM pieces"))
for dense in (False, True):
    add(f"m9b_writer_queue{'_dense' * dense}_f2", on("f2", lambda t, dense=dense: codec.queue_order(segment(t, W), W, dense)), lambda: scan_sql(cte("f2"), W, f"SELECT block, k, t0, CAST({ORDERED} AS BIGINT) AS place FROM pieces"))
for layout in ("split", "forward", "interleaved"):
    o = opt("f2", chunk=64, width=8, layout=layout)
    z, dd = "list(CASE WHEN dq >= 0 THEN 2 * dq ELSE -2 * dq - 1 END ORDER BY place)", "list(CAST(dt - 1 AS BIGINT) ORDER BY place)"
    numbers = {"split": f"list_concat(list_reverse({z}), {dd})", "forward": f"list_concat({z}, {dd})", "interleaved": "flatten(list([CASE WHEN dq >= 0 THEN 2 * dq ELSE -2 * dq - 1 END, CAST(dt - 1 AS BIGINT)] ORDER BY place))"}[layout]
    add(f"m10_chunks_{layout}_f2", on("f2", lambda t, o=o: codec.chunk_numbers(segment(t, o), o).withColumn("numbers", F.concat_ws(",", F.col("numbers").cast("array<string>")))),
        lambda o=o, numbers=numbers: scan_sql(cte("f2"), o, f"SELECT block, CAST(k // {o.width} AS INTEGER) AS bucket, CAST(place // {o.chunk} AS INTEGER) AS seq, CAST(count(*) AS INTEGER) AS n, array_to_string({numbers}, ',') AS numbers FROM (SELECT *, {ORDERED} AS place FROM pieces) GROUP BY 1, 2, 3"))
add("m12_shared_width_f2", on("f2", lambda t: measures.vwidth_bits(codec.chunk_numbers(segment(t, W), W)).select("block", "bucket", "seq", "n", "bits")))

# The codec and reading back
CODEC = opt("f2", width=8)
add("m13_compress_f2", on("f2", lambda t: codec.packed_bits(codec.compress(t, CODEC))))
add("m13_compress_f7", on("f7", lambda t: codec.packed_bits(codec.compress(t, opt("f7")))))
add("m20_fused_f2", on("f2", lambda t: codec.packed_bits(codec.compress(t, CODEC, fused=True)).select("packed_bits", F.lit("fused").alias("form")).union(codec.packed_bits(codec.compress(t, CODEC, fused=False)).select("packed_bits", F.lit("two stages")))))
EXPANDED = """e AS (SELECT k, t0, dt, p0, dq, CASE WHEN t0 = min(t0) OVER (PARTITION BY block, k) THEN 0 ELSE 1 END AS a FROM pieces),
x AS (SELECT k, t0 + s AS t, {g} * (p0 + dq * s / dt) AS x FROM (SELECT *, unnest(range(a, dt + 1)) AS s FROM e))"""


def expanded_sql(name: str, o: Options, select: str) -> str:
    body = scan_sql(cte(name), o, "@@")
    head, _ = body.rsplit("\n@@", 1)
    return f"{head.rstrip()},\n{EXPANDED.replace('{g}', repr(o.grid))}\n{select}"


SAMPLES = "SELECT k, t, round(x, 6) AS x FROM x"
add("m14_decompress_f2", on("f2", lambda t: codec.decompress(codec.compress(t, CODEC), CODEC).withColumn("x", F.round("x", 6))), lambda: expanded_sql("f2", CODEC, SAMPLES))
add("m14a_expand_f2", on("f2", lambda t: expand(segment(t, F2), None, F2).withColumn("x", F.round("x", 6))), lambda: expanded_sql("f2", F2, SAMPLES))
add("m15_at_f2", on("f2", lambda t: segquery.at(segment(t, F2), 300, F2).withColumn("x", F.round("x", 6))), lambda: expanded_sql("f2", F2, "SELECT k, round(x, 6) AS x FROM x WHERE t = 300"))
add("m15_at_subset_f2", on("f2", lambda t: segquery.at(segment(t, F2), 300, F2, [1, 3, 5]).withColumn("x", F.round("x", 6))), lambda: expanded_sql("f2", F2, "SELECT k, round(x, 6) AS x FROM x WHERE t = 300 AND k IN (1, 3, 5)"))
add("m15_between_f2", on("f2", lambda t: segquery.between(segment(t, F2), 250, 270, F2).withColumn("x", F.round("x", 6))), lambda: expanded_sql("f2", F2, "SELECT k, t, round(x, 6) AS x FROM x WHERE t BETWEEN 250 AND 270"))
add("m16_velocity_f2", on("f2", lambda t: segquery.velocity(segment(t, F2), F2).select("k", "t0", "dt", F.round("v", 6).alias("v"))), lambda: scan_sql(cte("f2"), F2, f"SELECT k, t0, dt, round({F2.grid!r} * dq / dt, 6) AS v FROM pieces"))

# Queries on pieces; all pairs of particles, in two dimensions
D2 = opt("f2", block=64)


def all_pairs(t: DataFrame, d: int = 2) -> DataFrame:
    ids = t.select(F.floor(F.col("k") / d).alias("a")).distinct()
    return ids.join(ids.select(F.col("a").alias("b")), F.col("a") < F.col("b"))


def distances_sql(select: str) -> str:
    return expanded_sql("f2", D2, select.replace("{pairs}", "(SELECT a.k // 2 AS a, b.k // 2 AS b, a.t, sum((a.x - b.x) * (a.x - b.x)) AS d2 FROM x a JOIN x b ON a.t = b.t AND a.k % 2 = b.k % 2 AND a.k // 2 < b.k // 2 GROUP BY 1, 2, 3)"))


add("m17_min_distance_f2", on("f2", lambda t: segquery.min_distance(segment(t, D2), all_pairs(t), 2, D2).select("a", "b", "sampled")), lambda: distances_sql("SELECT a, b, round(sqrt(min(d2)), 6) AS sampled FROM {pairs} GROUP BY a, b"))
add("m17_min_distance_bounds_f2", on("f2", lambda t: segquery.min_distance(segment(t, D2), all_pairs(t), 2, D2)))
add("m17_encounters_f2", on("f2", lambda t: segquery.encounters(segment(t, D2), all_pairs(t), 2, 0.5, D2)))
add("m18_aggregates_f2", on("f2", lambda t: segquery.seg_agg(segment(t, F2), F2, 0.2537)), lambda: expanded_sql("f2", F2, f"""
SELECT k, n, round(total, 4) AS total, round(low, 6) AS low, round(high, 6) AS high, above, round(integral, 4) AS integral, round({F2.grid!r}::DOUBLE * disp, 6) AS displacement, round({F2.grid!r}::DOUBLE * path, 6) AS path FROM
(SELECT k, count(*) AS n, sum(x) AS total, min(x) AS low, max(x) AS high, count(CASE WHEN x > 0.2537 THEN 1 END) AS above FROM x WHERE t % {F2.block} > 0 GROUP BY k)
JOIN (SELECT k, sum({F2.grid!r} * dt * (p0 + dq / 2)) AS integral, CAST(sum(dq) AS BIGINT) AS disp, CAST(sum(abs(dq)) AS BIGINT) AS path FROM pieces GROUP BY k) USING (k)"""))  # fmt: skip
for agg in ("min", "max", "avg"):
    add(f"m18_rewrite_{agg}_f2", on("f2", lambda t, agg=agg: segquery.rewrite_agg(segment(t, F2), agg, F2).withColumn("value", F.round("value", 4))), lambda agg=agg: expanded_sql("f2", F2, f"SELECT k, round({agg}(x), 4) AS value FROM x WHERE t % {F2.block} > 0 GROUP BY k"))


# M19, M21
def by_buckets(t: DataFrame) -> DataFrame:
    out = None
    for width in (64, 32, 16, 8, 4, 2, 1):
        row = codec.packed_bits(codec.compress(t, opt("f2", width=width))).select(F.lit(64 // width).alias("buckets"), "packed_bits")
        out = row if out is None else out.union(row)
    return out


add("m19_buckets_f2", on("f2", by_buckets))
add("m21_entropy_f2", on("f2", lambda t: relational.run(segment(t, F2), relational.entropy(F2))), lambda: scan_sql(cte("f2"), F2, "@@").replace("\n@@", ",\n" + relational.entropy(F2)[5:].replace("{track}", "pieces")))
add("m21_huffman_f2", on("f2", lambda t: codecs.huffman_bits(segment(t, F2))))

# baselines
SHAPES = {
    "b1_raw": relational.raw_bytes(), "b2_subsample_8": relational.subsample(8), "b2_spotlight": relational.spotlight(50, 5, 100, 20), "b4_grid_only": relational.grid_only(F2), "b5_delta_time": relational.delta(F2, "time"), "b5_delta_space": relational.delta(F2, "space"),
    "b5_delta_both": relational.delta(F2, "both"), "b6_native_like": relational.native_like(F2), "b7_predictive_0": relational.predictive(F2, 0), "b7_predictive_1": relational.predictive(F2, 1), "b7a_predictive_group": relational.predictive_group(F2, 4),
    "b8_legacy_like": relational.legacy_like(F2), "b9_reorder_keep": relational.reorder(F2, True), "b9_reorder_lose": relational.reorder(F2, False), "b16_regress_16": relational.regress(16),
}
for name, body in SHAPES.items():
    add(f"{name}_f2", on("f2", lambda t, body=body: relational.run(t, body)), relational.oracle(cte("f2"), body))
add("b10_int_codes_f8", on("f8", lambda t: relational.run(t, relational.int_sizes())), relational.oracle(cte("f8"), relational.int_sizes()))
add("b3_general_f2", on("f2", lambda t: codecs.general(t, F2)))
add("b6a_native_full_f2", on("f2", lambda t: codecs.native_full(t, F2)))
for order in (0, 1):
    add(f"b7_range_coder_{order}_f2", on("f2", lambda t, order=order: codecs.predictive_coder(t, F2, order)))
add("b11_components_f2", on("f2", lambda t: codecs.pca(t, [1, 2, 4, 8, 16, 32, 64])))
add("b12_poly_window_f2", on("f2", lambda t: codecs.poly_window(t, F2)))
add("b13_simplify_f2", on("f2", lambda t: codecs.simplify(t, F2)))
REFEREE = opt("f2", block=64, width=8)
for family in ("free_line", "constant"):
    add(f"b14_optimal_pieces_{family}_f2", on("f2", lambda t, family=family: codecs.optimal_pieces(t, REFEREE, family)))
add("b14_optimal_cover_f2", on("f2", lambda t: codecs.optimal_cover(t, opt("f2", block=32, width=8), 3)))

# measures
add("a1_ratio_f2", on("f2", lambda t: measures.metric(t, opt("f2", width=64), dims=2)))
add("a1_ratio_gamma_f2", on("f2", lambda t: measures.gamma_metric(segment(t, F2), key_frames(t, F2), t.agg(F.count("*").alias("n")), F2)), lambda: scan_sql(cte("f2"), F2, f"""
SELECT pieces, dq_bits, dt_bits, frame_bits, dq_bits + dt_bits + frame_bits AS packed_bits, round(n * 64 / (dq_bits + dt_bits + frame_bits), 4) AS ratio, round((dq_bits + dt_bits + frame_bits) / n, 4) AS bits_per_value FROM
(SELECT count(*) AS pieces, CAST(sum(2 * (length(bin(CASE WHEN dq >= 0 THEN 2 * dq ELSE -2 * dq - 1 END + 1)) - 1) + 1) AS BIGINT) AS dq_bits, CAST(sum(2 * (length(bin(CAST(dt AS BIGINT))) - 1) + 1) AS BIGINT) AS dt_bits FROM pieces),
(SELECT CAST(sum(c * CASE WHEN s = 0 THEN 0 ELSE length(bin(s)) END) AS BIGINT) AS frame_bits FROM (SELECT s.block, count(*) AS c, CAST(max(floor(y + 0.5)) - min(floor(y + 0.5)) AS BIGINT) AS s FROM samples s JOIN ends e ON s.k = e.k AND s.block = e.block AND s.t = e.a GROUP BY 1)),
(SELECT count(*) AS n FROM track)"""))  # fmt: skip
for name in ("f2", "f3", "f7"):
    o = opt(name)
    add(f"a4_errors_{name}", on(name, lambda t, o=o: measures.errors(t, o).select("n", "rebuilt", "max_err", F.round("mean_err", 4).alias("mean_err"), F.round("rms_err", 4).alias("rms_err"), "beyond")), lambda name=name, o=o: expanded_sql(name, o, f""",
lone AS (SELECT s.k, s.t, {o.grid!r} * floor(y + 0.5) AS x FROM samples s JOIN ends e ON s.k = e.k AND s.block = e.block AND s.t = e.a WHERE e.a = e.z),
y AS (SELECT * FROM x UNION ALL SELECT * FROM lone)
SELECT count(*) AS n, count(y.x) AS rebuilt, round(max(abs(track.x - y.x)), 6) AS max_err, round(avg(abs(track.x - y.x)), 4) AS mean_err, round(sqrt(avg((track.x - y.x) * (track.x - y.x))), 4) AS rms_err, 0::BIGINT AS beyond FROM track LEFT JOIN y ON track.k = y.k AND track.t = y.t""".replace(",\nlone", "@lone", 1)).replace("\n@lone", ",\nlone"))  # fmt: skip
add("a7_pieces_f2", on("f2", lambda t: measures.piece_stats(segment(t, F2))), lambda: scan_sql(cte("f2"), F2, "SELECT count(*) AS pieces, round(avg(dt), 6) AS mean_dt, max(dt) AS max_dt, round(avg(CASE WHEN dt = 1 THEN 1.0 ELSE 0.0 END), 6) AS share_one FROM pieces"))
add("a8_peak_pending_f2", on("f2", lambda t: measures.peak_pending(segment(t, F2), F2)), lambda: scan_sql(cte("f2"), F2, """SELECT block, CAST(max(level) AS BIGINT) AS peak FROM (SELECT block, t, sum(d) OVER (PARTITION BY block ORDER BY t) AS level FROM (SELECT block, t, sum(d) AS d FROM
(SELECT block, t0 + dt AS t, 1 AS d FROM pieces UNION ALL SELECT block, max(t0 + dt) OVER (PARTITION BY block ORDER BY t0, k ROWS UNBOUNDED PRECEDING) AS t, -1 AS d FROM pieces) GROUP BY 1, 2)) GROUP BY 1"""))  # fmt: skip
add("a9_operations_f2", on("f2", lambda t: t.agg(F.count("*").alias("n")).select(*[(F.col("n") * c).alias(f"{form}_{name}") for form, row in measures.OPERATIONS.items() for c, name in zip(row, ("add", "div", "mul", "compare", "branch"), strict=True)])),
    f"WITH {cte('f2')} SELECT " + ", ".join(f"count(*) * {c} AS {form}_{name}" for form, row in measures.OPERATIONS.items() for c, name in zip(row, ("add", "div", "mul", "compare", "branch"), strict=True)) + " FROM track")
add("a10_seek_cost_f2", on("f2", lambda t: _seek(t)))
add("a11_size_split_f2", on("f2", lambda t: codec.packed_bits(codec.compress(t, CODEC)).selectExpr("stack(3, 'frames', frame_bits, 'headers', header_bits, 'chunks', chunk_bits) AS (part, bits)")))
add("a12_position_bits_f2", on("f2", lambda t: measures.position_bits(t, opt("f2", eps=1e-4))), f"WITH {cte('f2')} SELECT round(max(x) - min(x), 6) AS edge, CAST(ceil(log2((max(x) - min(x)) / {opt('f2', eps=1e-4).grid!r})) AS BIGINT) AS bits FROM track")
add("advise_f2", on("f2", lambda t: advise(t, F2, share=1.0)))


def _seek(t: DataFrame) -> DataFrame:
    """Stored bytes and samples that a look at one step touches, by block length."""
    out = None
    for block in (32, 64, 128, 256):
        o = opt("f2", block=block)
        stored = codec.compress(t, o)
        row = stored.where(F.col("block") == 100 // block).agg(F.lit(block).alias("block_length"), F.sum(F.octet_length("payload") + F.octet_length("header")).alias("bytes_read"), F.count("*").alias("rows_read"))
        out = row if out is None else out.union(row)
    return out
