"""Named queries over the given tables, each with its SQL twin where SQL can express it."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from padgrad.functions import fixedpoint as fx
from padgrad.functions import keys
from padgrad.functions.vectors import argmax, dot
from padgrad.operators import baselines, gradcode, latency, measures, moments, sharing
from padgrad.operators.training import CodedTables, train_coded, train_coded_spark
from padgrad.plans import oracles as o
from padgrad.plans import planner, workloads
from padgrad.shared import written
from padgrad.sources.devices import fleet as fleet_of
from padgrad.sources.devices import split_sorted as split_by_label
from padgrad.sources.features import rbf_features, rbf_features_sql, text_histograms
from padgrad.sources.tables import read_table, write_by_device
from padgrad.streaming import arrivals

D, DIMS, SEED = 25, 64, "pad-1"
D5, ALPHA5, LANES = 5, 3, len(fx.PRIMES)
#: Code of the cell queries, and the devices whose answers come first there.
ALPHA = 6
ARRIVED = tuple(i for i in range(25) if i not in (1, 4, 9, 16, 22))
EPOCHS, LAT_SEED = 30, "lat-1"
RHO, BITS = float(latency.mac_count("coded", 2000, 10)), float(latency.message_bits(2000, 10, 48))
ALPHAS = (6, 16, 23, 25)
QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


def field_codes() -> list[np.ndarray]:
    return [gradcode.field_encoder(D, ALPHA, p, seed=4) for p in fx.PRIMES]


def eps_table(spark: SparkSession) -> DataFrame:
    k = spark.range(DIMS).select(F.col("id").cast("int").alias("k"), F.explode(F.sequence(F.lit(0), F.lit(9))).alias("j"))
    return k.withColumn("e", (F.pmod(F.col("k") * 7 + F.col("j") * 3, F.lit(11)) - 5).cast("long"))


# --- fixed point and pads ------------------------------------------------------------------


@query(f"""WITH q AS (SELECT l_orderkey, l_linenumber, {o.quant('l_extendedprice')} AS a_fx, {o.quant('l_discount - 0.05')} AS b_fx FROM lineitem)
SELECT l_orderkey, l_linenumber, a_fx, b_fx, {o.wrap('a_fx + b_fx')} AS sum_fx, {o.mul('a_fx', 'b_fx')} AS prod_fx, {o.wrap('a_fx::HUGEINT * 1000')} AS wrapped FROM q""")
def fx_ops(spark, sf_dir):
    t = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_extendedprice", "l_discount")
    t = t.select("l_orderkey", "l_linenumber", fx.quantise(F.col("l_extendedprice")).alias("a_fx"), fx.quantise(F.col("l_discount") - 0.05).alias("b_fx"))
    a, b = F.col("a_fx"), F.col("b_fx")
    return t.select("*", fx.fx_add(a, b).alias("sum_fx"), fx.fx_mul(a, b).alias("prod_fx"), fx.wrap(a * 1000).alias("wrapped"))


@query(f"WITH c AS (SELECT vec_id, unnest(embedding)::DOUBLE AS x FROM embeddings), q AS (SELECT vec_id, {o.quant('x')} AS a, {o.quant('x * 3 - 1')} AS b FROM c) SELECT vec_id, {o.wrap(f'sum({o.mul("a", "b")})')} AS dot_fx FROM q GROUP BY 1")
def fx_dots(spark, sf_dir):
    """Dot products in fixed point: every product is floored by itself."""
    t = read_table(spark, sf_dir, "embeddings", "vec_id", "embedding")
    a, b = (fx.quantise_vector(F.transform("embedding", f)) for f in (lambda v: v.cast("double"), lambda v: v.cast("double") * 3 - 1))
    return t.select("vec_id", fx.fx_dot(a, b).alias("dot_fx"))


_FS = (8, 16, 24)


@query("WITH c AS (SELECT unnest(embedding)::DOUBLE AS x FROM embeddings) " + " UNION ALL ".join(
    f"SELECT {f} AS f, round(max(abs(x - {o.quant('x', f=f)} / {float(2**f)!r})) * {float(2**f)!r}, 6) AS max_abs_err_scaled, count(*) AS cells FROM c" for f in _FS))
def fx_roundtrip_error(spark, sf_dir):
    x = read_table(spark, sf_dir, "embeddings", "embedding").select(F.explode("embedding").alias("v")).select(F.col("v").cast("double").alias("x"))
    parts = [x.agg(F.lit(f).alias("f"), F.round(F.max(F.abs(F.col("x") - fx.dequantise(fx.quantise(F.col("x"), f=f), f))) * float(2**f), 6).alias("max_abs_err_scaled"), F.count("*").alias("cells")) for f in _FS]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query(f"""SELECT d.range::INT AS device, i.range::INT AS i, j.range::INT AS j, {o.pad(SEED, 'd.range', 'xi', 'i.range', 'j.range')} AS pad
FROM (SELECT r_regionkey AS range FROM region) d, range({DIMS}) i, range({DIMS}) j""")
def pad_cells(spark, sf_dir):
    base = read_table(spark, sf_dir, "region", "r_regionkey").select(F.col("r_regionkey").cast("int").alias("device"), F.explode(F.sequence(F.lit(0), F.lit(DIMS - 1))).alias("i"))
    base = base.select("*", F.explode(F.sequence(F.lit(0), F.lit(DIMS - 1))).alias("j"))
    return base.withColumn("pad", keys.pad_cell(SEED, F.col("device"), keys.XI, F.col("i"), F.col("j")))


@query(f"""WITH {o.examples(D)} SELECT device, i, j, {o.wrap('v + ' + o.pad(SEED, 'device', 'xi', 'i', 'j'))} AS padded FROM gram""")
def padded_moments(spark, sf_dir):
    cells = moments.gram_cells(workloads.integer_examples(spark, sf_dir))
    return cells.select("device", "i", "j", keys.apply_pad(F.col("v"), keys.pad_cell(SEED, F.col("device"), keys.XI, F.col("i"), F.col("j"))).alias("padded"))


_MODES = (("fraction", 0.37), ("integer", 3.0))


def _retrieval_sql() -> str:
    k, f = 32, 16
    out = []
    for mode, c in _MODES:
        cm = int(np.floor(c * 2**f + 0.5))
        share = o.wrap("x + r", k)
        err = o.wrap(f"{o.wrap(o.mul(str(cm), share, k, f) + ' - ' + o.mul(str(cm), 'r', k, f), k)} - {o.mul(str(cm), 'x', k, f)}", k)
        out.append(f"SELECT '{mode}' AS mode, count(*) AS cells, count(*) FILTER ({share} <> x + r) AS wraps, count(*) FILTER (abs({err}) > 1) AS wrong, max(abs({err})) AS max_ulp FROM c")
    return f"""WITH c AS (SELECT {o.quant('embedding[i + 1]::DOUBLE * 500', f=f)} AS x, {o.pad(SEED, 'vec_id', 'delta', 'i', '0', k)} AS r
FROM embeddings, (SELECT range::INT AS i FROM range(64))) """ + " UNION ALL ".join(out)


@query(_retrieval_sql())
def retrieval_error(spark, sf_dir):
    k, f = 32, 16
    t = read_table(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", F.posexplode("embedding").alias("i", "v"))
    t = t.select(fx.quantise(F.col("v").cast("double") * 500, k, f).alias("x"), keys.pad_cell(SEED, F.col("vec_id"), keys.DELTA, F.col("i"), F.lit(0), k).alias("r"))
    modes = F.explode(F.array(*[F.struct(F.lit(m).alias("mode"), F.lit(int(np.floor(c * 2**f + 0.5))).cast("long").alias("c")) for m, c in _MODES])).alias("m")
    t = t.withColumn("share", fx.wrap(F.col("x") + F.col("r"), k)).select("*", modes).withColumn("c", F.col("m.c"))
    got = keys.retrieve(fx.fx_scale(F.col("c"), F.col("share"), k, f), fx.fx_scale(F.col("c"), F.col("r"), k, f), k)
    diff = fx.wrap(got - fx.fx_mul(F.col("c"), F.col("x"), k, f), k)
    return measures.retrieval_error(t.select(F.col("m.mode").alias("mode"), (F.col("share") != F.col("x") + F.col("r")).alias("wrapped"), diff.alias("diff")))


@query(f"""WITH c AS (SELECT {o.wrap(o.quant('embedding[i + 1]::DOUBLE') + ' + ' + o.pad(SEED, 'vec_id', 'delta', 'i', '0'))} AS share
FROM embeddings, (SELECT range::INT AS i FROM range(64))) SELECT ((share + {2**47}) // {2**42})::INT AS bucket, count(*) AS n FROM c GROUP BY 1""")
def pad_uniformity(spark, sf_dir):
    return keys.uniformity(_shares(spark, sf_dir))


def _shares(spark, sf_dir):
    t = read_table(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", F.posexplode("embedding").alias("i", "v"))
    secret = fx.quantise(F.col("v").cast("double"))
    return t.select(secret.alias("secret"), keys.apply_pad(secret, keys.pad_cell(SEED, F.col("vec_id"), keys.DELTA, F.col("i"), F.lit(0))).alias("share"))


@query(f"""WITH c AS (SELECT {o.quant('embedding[i + 1]::DOUBLE')} AS secret, {o.wrap(o.quant('embedding[i + 1]::DOUBLE') + ' + ' + o.pad(SEED, 'vec_id', 'delta', 'i', '0'))} AS share
FROM embeddings, (SELECT range::INT AS i FROM range(64))) SELECT round(corr(secret::DOUBLE, share::DOUBLE), 6) AS correlation, count(*) AS n FROM c""")
def share_correlation(spark, sf_dir):
    return measures.share_correlation(_shares(spark, sf_dir)).withColumn("correlation", F.round("correlation", 6))


# --- codes ---------------------------------------------------------------------------------


@query("""SELECT a.n_nationkey::INT AS device, s.range::INT AS slot, ((a.n_nationkey + s.range) % 25)::INT AS peer FROM nation a, range(6) s""")
def cyclic_support(spark, sf_dir):
    n = read_table(spark, sf_dir, "nation", "n_nationkey").count()
    return gradcode.cyclic_support(spark, n, 6)


@query("""SELECT a.n_nationkey::INT AS device, ((b.n_nationkey - a.n_nationkey + 25) % 25)::INT AS slot, b.n_nationkey::INT AS peer
FROM nation a, nation b WHERE (b.n_nationkey - a.n_nationkey + 25) % 25 < 6""")
def support_by_distance(spark, sf_dir):
    a = read_table(spark, sf_dir, "nation", "n_nationkey").select(F.col("n_nationkey").cast("int").alias("device"))
    b = a.select(F.col("device").alias("peer"))
    slot = F.pmod(F.col("peer") - F.col("device"), F.lit(25))
    return a.join(F.broadcast(b), slot < 6).select("device", slot.alias("slot"), "peer")


def _decoder_sql() -> str:
    """Decode weights of all three-of-five patterns: normal equations solved by Cramer's rule."""
    b5 = gradcode.build_encoder(D5, ALPHA5, seed=2)
    rows = ", ".join(f"({i}, {j}, {float(b5[i, j])!r}::DOUBLE)" for i in range(D5) for j in range(D5))
    return f"""WITH code(device, peer, b) AS (VALUES {rows}), ones AS (SELECT device, sum(b) AS r FROM code GROUP BY 1),
g AS (SELECT x.device AS p, y.device AS q, sum(x.b * y.b) AS v FROM code x JOIN code y USING (peer) GROUP BY ALL),
tri AS (SELECT row_number() OVER (ORDER BY a.device, b.device, c.device) - 1 AS pattern_id, [a.device, b.device, c.device] AS s FROM ones a, ones b, ones c WHERE a.device < b.device AND b.device < c.device),
m AS (SELECT pattern_id, s, (SELECT r FROM ones WHERE device = s[1]) AS r1, (SELECT r FROM ones WHERE device = s[2]) AS r2, (SELECT r FROM ones WHERE device = s[3]) AS r3,
  {', '.join(f"(SELECT v FROM g WHERE p = s[{i}] AND q = s[{j}]) AS m{i}{j}" for i in (1, 2, 3) for j in (1, 2, 3))} FROM tri),
d AS (SELECT *, m11 * (m22 * m33 - m23 * m32) - m12 * (m21 * m33 - m23 * m31) + m13 * (m21 * m32 - m22 * m31) AS det FROM m),
w AS (SELECT pattern_id, s[1] AS device, (r1 * (m22 * m33 - m23 * m32) - m12 * (r2 * m33 - m23 * r3) + m13 * (r2 * m32 - m22 * r3)) / det AS coef FROM d
  UNION ALL SELECT pattern_id, s[2], (m11 * (r2 * m33 - m23 * r3) - r1 * (m21 * m33 - m23 * m31) + m13 * (m21 * r3 - r2 * m31)) / det FROM d
  UNION ALL SELECT pattern_id, s[3], (m11 * (m22 * r3 - r2 * m32) - m12 * (m21 * r3 - r2 * m31) + r1 * (m21 * m32 - m22 * m31)) / det FROM d)"""


@query(_decoder_sql() + " SELECT pattern_id, device::INT AS device, round(coef, 5) AS coef_r5 FROM w")
def decoder_weights(spark, sf_dir):
    """Decode weights of every straggler pattern, solved in parallel."""
    n = read_table(spark, sf_dir, "region", "r_regionkey").count()
    return gradcode.build_decoder(spark, gradcode.build_encoder(n, ALPHA5, seed=2), ALPHA5).select("pattern_id", "device", F.round("coef", 5).alias("coef_r5"))


@query(_decoder_sql() + " SELECT pattern_id, peer::INT AS peer, round(sum(coef * b), 6) AS value_r6 FROM w JOIN code USING (device) GROUP BY ALL")
def code_identity(spark, sf_dir):
    """Entries of A B for every straggler pattern."""
    n = read_table(spark, sf_dir, "region", "r_regionkey").count()
    b = gradcode.build_encoder(n, ALPHA5, seed=2)
    out = gradcode.verify_code(gradcode.build_decoder(spark, b, ALPHA5), gradcode.encoder_table(spark, b))
    return out.select("pattern_id", "peer", F.round("value", 6).alias("value_r6"))


@query()
def code_conditioning(spark, sf_dir):
    """Worst decode weights and residuals for each alpha: over all patterns where a decoder table is built (up to 100 000), over 200 drawn ones else (``sampled``)."""
    n, out = read_table(spark, sf_dir, "nation", "n_nationkey").distinct().count(), None  # a device for each nation
    for a in (1, 2, *ALPHAS):
        b = gradcode.build_encoder(n, a, 1)
        if planner.decoder_plan(n, a) == "table":
            part = gradcode.table_conditioning(spark, b, a).select(F.lit(a).alias("alpha"), "patterns", F.lit(False).alias("sampled"), "residual", "largest", "weight_sum")
        else:
            worst = gradcode.conditioning(b, a, 200)
            part = spark.createDataFrame([(a, 200, True, worst["residual"], worst["largest"], worst["sum"])], "alpha int, patterns long, sampled boolean, residual double, largest double, weight_sum double")
        out = part if out is None else out.unionByName(part)
    return out


# --- splits and moments ----------------------------------------------------------------------


@query(f"WITH {o.examples(D)} SELECT device, count(*) AS n, min(label)::INT AS min_label, max(label)::INT AS max_label FROM ex GROUP BY 1")
def device_sizes(spark, sf_dir):
    return workloads.integer_examples(spark, sf_dir).groupBy("device").agg(F.count("*").alias("n"), F.min("label").cast("int").alias("min_label"), F.max("label").cast("int").alias("max_label"))


@query(f"WITH {o.examples(D)} SELECT vec_id, device FROM ex")
def split_sorted(spark, sf_dir):
    return workloads.integer_examples(spark, sf_dir).select("vec_id", "device")


@query("SELECT c_nationkey::INT AS device, count(*) AS n, count(DISTINCT o_orderkey) AS orders FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def device_rows_by_nation(spark, sf_dir):
    line = read_table(spark, sf_dir, "lineitem", "l_orderkey")
    per = line.groupBy("l_orderkey").agg(F.count("*").alias("lines"))
    orders = read_table(spark, sf_dir, "orders", "o_orderkey", "o_custkey").hint("merge")
    customer = read_table(spark, sf_dir, "customer", "c_custkey", "c_nationkey").hint("shuffle_hash")
    rows = per.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    return rows.groupBy(F.col("c_nationkey").cast("int").alias("device")).agg(F.sum("lines").alias("n"), F.count("*").alias("orders"))


@query(f"WITH {o.examples(D)} SELECT device, i, j, v AS v_fx FROM gram")
def gram_cells(spark, sf_dir):
    return moments.gram_cells(workloads.integer_examples(spark, sf_dir)).withColumnRenamed("v", "v_fx")


@query(f"WITH {o.examples(D)} SELECT device, i, j, v AS v_fx FROM gram")
def gram_cells_arrow(spark, sf_dir):
    """The Arrow engine's sums, as cells: exact here since integers below 2^53 are doubles."""
    rows = workloads.integer_examples(spark, sf_dir)
    to = lambda c: F.transform(c, lambda v: v.cast("double"))
    m = moments.device_moments(rows.select("device", to("x").alias("x"), to("y").alias("y")), DIMS, 10)
    return m.select("device", "i", F.posexplode("g").alias("j", "v")).select("device", "i", "j", F.col("v").cast("long").alias("v_fx"))


@query(f"WITH {o.examples(D)} SELECT device, i, j, v AS v_fx FROM crs")
def cross_cells(spark, sf_dir):
    return moments.cross_cells(workloads.integer_examples(spark, sf_dir)).withColumnRenamed("v", "v_fx")


@query(f"WITH {o.examples(D)} SELECT device, i, j, -v AS g_fx FROM crs")
def first_gradient(spark, sf_dir):
    return moments.cross_cells(workloads.integer_examples(spark, sf_dir)).select("device", "i", "j", (-F.col("v")).alias("g_fx"))


# --- sharing and coded answers -----------------------------------------------------------------


def _plain_cells(spark, sf_dir):
    rows = workloads.integer_examples(spark, sf_dir)
    xi = moments.gram_cells(rows).withColumn("part", F.lit(keys.XI))
    delta = moments.cross_cells(rows).select("device", "i", "j", (-F.col("v")).alias("v"), F.lit(keys.DELTA).alias("part"))
    return xi.unionByName(delta)


def _coded(spark, sf_dir):
    return sharing.encode(sharing.pad_shares(_plain_cells(spark, sf_dir), SEED, LANES), sharing.lane_code(spark, field_codes()), LANES)


def _key_answers(spark):
    coded = sharing.encode(sharing.key_cells(spark, SEED, D, DIMS, 10, LANES), sharing.lane_code(spark, field_codes()), LANES)
    return sharing.answers(coded, eps_table(spark), LANES)


def _lane_pad(kind):
    a, b = ("least(i, j)", "greatest(i, j)") if kind == "xi" else ("i", "j")
    return o.prf(f"sha256(concat_ws(':', '{SEED}', 'device', device))", f"'{kind}'", a, b, "lane")


_CODED_SQL = f"""WITH {o.examples(D)}, {o.code_values(field_codes())}, {o.eps_sql(DIMS)}, lanes AS (SELECT range::INT AS lane FROM range({LANES})),
cells AS (SELECT device, 'xi' AS part, i, j, v FROM gram UNION ALL SELECT device, 'delta', i, j, -v FROM crs),
shares AS (SELECT device AS peer, part, i, j, lane, {o.mod(f"v::HUGEINT + CASE part WHEN 'xi' THEN {_lane_pad('xi')} ELSE {_lane_pad('delta')} END", o.PRIME_OF)} AS v FROM cells, lanes),
coded AS (SELECT device, part, i, j, lane, {o.mod('sum(b::HUGEINT * v)', o.PRIME_OF)} AS coded FROM shares JOIN code USING (peer, lane) GROUP BY device, part, i, j, lane)"""
_PLAIN_SQL = f"""WITH {o.examples(D)}, {o.code_values(field_codes())}, {o.eps_sql(DIMS)},
grad AS (SELECT device AS peer, i, j, sum(v)::HUGEINT AS v FROM (
  SELECT device, g.i, e.j, g.v::HUGEINT * e.e AS v FROM gram g JOIN eps e ON g.j = e.k UNION ALL SELECT device, i, j, -v::HUGEINT FROM crs) GROUP BY ALL)"""


@query(_CODED_SQL + " SELECT * FROM coded")
def encode_shares(spark, sf_dir):
    return _coded(spark, sf_dir).withColumnRenamed("v", "coded")


@query(_CODED_SQL + f""" SELECT device, i, j, lane, {o.mod('sum(v)', o.PRIME_OF)} AS v FROM (
  SELECT device, c.i, e.j, lane, coded::HUGEINT * e.e AS v FROM coded c JOIN eps e ON c.j = e.k WHERE part = 'xi'
  UNION ALL SELECT device, i, j, lane, coded FROM coded WHERE part = 'delta') GROUP BY device, i, j, lane""")
def coded_answer(spark, sf_dir):
    return sharing.answers(_coded(spark, sf_dir), eps_table(spark), LANES)


@query(_PLAIN_SQL + f" SELECT device, i, j, lane, {o.mod('sum(b::HUGEINT * v)', o.PRIME_OF)} AS v FROM grad JOIN code USING (peer) GROUP BY device, i, j, lane")
def unpadded_answer(spark, sf_dir):
    return sharing.unpad(sharing.answers(_coded(spark, sf_dir), eps_table(spark), LANES), _key_answers(spark), LANES)


def _decoded(spark, sf_dir, arrived=ARRIVED):
    clear = sharing.unpad(sharing.answers(_coded(spark, sf_dir), eps_table(spark), LANES), _key_answers(spark), LANES)
    weights = [gradcode.field_decode_vector(b, arrived, p) for b, p in zip(field_codes(), fx.PRIMES, strict=False)]
    return sharing.signed_two_lanes(sharing.decode(clear.where(F.col("device").isin(*arrived)), weights, LANES))


@query(_PLAIN_SQL + " SELECT i, j, sum(v)::BIGINT AS sum_fx FROM grad GROUP BY ALL")
def decoded_gradient_cells(spark, sf_dir):
    """The whole coded path against the plain sum of all devices' gradients."""
    return _decoded(spark, sf_dir).withColumnRenamed("v", "sum_fx")


_NATION = """rows AS (SELECT c_nationkey::INT AS device, l_extendedprice / 1e5 AS p, l_discount AS q, l_tax AS t
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey),
nx AS (SELECT device, [p, 10 * p * q, 10 * p * t, 100 * p * q * t] AS x, p * (1 - q) * (1 + t) AS y FROM rows)"""


@query(f"""WITH {_NATION}, r AS (SELECT x, 0.5 * x[1] - 0.25 * x[2] + 0.125 * x[3] + 0.0625 * x[4] - y AS e FROM nx)
SELECT (i.range - 1)::INT AS i, 0 AS j, round(sum(x[i.range] * e), 4) AS v_r4 FROM r, range(1, 5) i GROUP BY i.range""")
def decoded_gradient_real(spark, sf_dir):
    """Padded lanes over nations on tables: any three of 25 answers give the sum (alpha = 23)."""
    theta = np.array([[0.5], [-0.25], [0.125], [0.0625]])
    tables = CodedTables(moments.device_moments(workloads.nation_examples(spark, sf_dir), 4, 1), D, 23, (4, 1), SEED)
    return tables.gradient_cells(theta, [3, 11, 20]).select("i", "j", F.round("v", 4).alias("v_r4"))


def _unrolled_sql() -> str:
    d, c, mu, lam = 64, 10, 6.0, workloads.LAMBDA
    base = f"""WITH e AS (SELECT vec_id, label, embedding FROM embeddings), n AS (SELECT count(*)::DOUBLE AS m FROM e),
di AS (SELECT range::INT AS i FROM range({d})), dj AS (SELECT range::INT AS j FROM range({c})),
g AS (SELECT a.i, b.i AS k, sum(embedding[a.i + 1]::DOUBLE * embedding[b.i + 1]::DOUBLE) AS v FROM e, di a, di b GROUP BY ALL),
h AS (SELECT i, j, sum(CASE WHEN label = j THEN embedding[i + 1]::DOUBLE ELSE 0 END) AS v FROM e, di, dj GROUP BY ALL),
t0 AS (SELECT i, j, 0.0::DOUBLE AS t FROM di, dj)"""
    for s in range(1, 4):  # the model is sent with 24 fraction bits
        base += f""", q{s} AS (SELECT i, j, floor(t * 16777216.0 + 0.5) / 16777216.0 AS t FROM t{s - 1}), t{s} AS (SELECT p.i, p.j, any_value(p.t) - {mu} * ((sum(g.v * q.t) - any_value(h.v)) / any_value(n.m) + {lam} * any_value(p.t)) AS t
  FROM q{s} p JOIN g ON g.i = p.i JOIN q{s} q ON q.i = g.k AND q.j = p.j JOIN h ON h.i = p.i AND h.j = p.j, n GROUP BY p.i, p.j)"""
    return base + " " + " UNION ALL ".join(f"SELECT {s} AS epoch, i, j, round(t, 4) AS theta_r4 FROM t{s}" for s in (1, 2, 3))


@query(_unrolled_sql())
def three_epochs_unrolled(spark, sf_dir):
    """Coded descent on tables: 25 devices, padded lanes, all dimensions, only three devices' folders read in an epoch; against plain descent written out in SQL."""
    d, c, out = 64, 10, []
    rows = read_table(spark, sf_dir, "embeddings", "vec_id", "embedding", "label")
    ex = split_by_label(rows, "label", "vec_id", D).select("device", F.transform("embedding", lambda v: v.cast("double")).alias("x"), F.transform(F.sequence(F.lit(0), F.lit(9)), lambda k: (k == F.col("label")).cast("double")).alias("y"))
    times = latency.np_epoch_times(latency.class_rates(D), 3, 1e6, 1e4, 5)
    train_coded_spark(moments.device_moments(ex, d, c), D, 23, ex.count(), (d, c), np.argsort(times, axis=1).tolist(), workloads.LAMBDA, lambda e: 6.0, SEED, evaluate=lambda t: out.append(t.copy()) or {})
    cells = [(e + 1, i, j, float(t[i, j])) for e, t in enumerate(out) for i in range(d) for j in range(c)]
    return spark.createDataFrame(cells, "epoch int, i int, j int, t double").select("epoch", "i", "j", F.round("t", 4).alias("theta_r4"))


# --- losses, features, accuracy ------------------------------------------------------------------

_THETA3 = np.array([[0.9], [-0.08], [0.07], [-0.005]])


@query(f"""WITH {_NATION}, s AS (SELECT device, (0.9 * x[1] - 0.08 * x[2] + 0.07 * x[3] - 0.005 * x[4] - y) ** 2 AS e FROM nx)
SELECT device, count(*) AS n, round(avg(e) / 2, 6) AS local_loss_r6, round((SELECT avg(e) FROM s) / 2 + 0.5 * {float((_THETA3**2).sum())!r}, 6) AS global_loss_r6 FROM s GROUP BY 1""")
def loss_decomposition(spark, sf_dir):
    ex = workloads.nation_examples(spark, sf_dir)
    local = moments.local_loss(ex, _THETA3)
    whole = moments.combine_losses(local, _THETA3, 1.0)
    return local.crossJoin(F.broadcast(whole)).select("device", "n", F.round("local_loss", 6).alias("local_loss_r6"), F.round("global_loss", 6).alias("global_loss_r6"))


@query(f"""WITH {_NATION}, r AS (SELECT x, 0.9 * x[1] - 0.08 * x[2] + 0.07 * x[3] - 0.005 * x[4] - y AS e FROM nx), t(i, theta) AS (VALUES (1, 0.9::DOUBLE), (2, -0.08), (3, 0.07), (4, -0.005))
SELECT (i - 1)::INT AS i, round(sum(x[i] * e) / count(*) + 0.01 * any_value(theta), 6) AS v_r6 FROM r, t GROUP BY i""")
def server_gradient(spark, sf_dir):
    """What the server makes of all devices' gradients: their mean over examples and the regulariser."""
    ex = workloads.nation_examples(spark, sf_dir)
    grads = moments.device_gradient(moments.device_moments(ex, 4, 1), _THETA3)
    out = moments.aggregate_gradient(grads, _THETA3, 0.01, ex.count())
    return spark.createDataFrame([(i, float(out[i, 0])) for i in range(4)], "i int, v double").select("i", F.round("v", 6).alias("v_r6"))


W3_EPOCHS, W3_MU = 200, 1.5


@query(f"""WITH RECURSIVE {_NATION}, ix AS (SELECT range AS i FROM range(1, 5)), n AS (SELECT count(*)::DOUBLE AS m, sum(y * y) AS yy FROM nx),
gc AS (SELECT a.i, b.i AS j, sum(x[a.i] * x[b.i]) AS v FROM nx, ix a, ix b GROUP BY ALL), gl AS (SELECT i, list(v ORDER BY j) AS line FROM gc GROUP BY 1),
mat AS MATERIALIZED (SELECT list(line ORDER BY i) AS g FROM gl), hc AS (SELECT i, sum(x[i] * y) AS v FROM nx, ix GROUP BY 1), vec AS MATERIALIZED (SELECT list(v ORDER BY i) AS h FROM hc),
path(epoch, theta) AS (SELECT 0, [0.0::DOUBLE, 0.0, 0.0, 0.0] UNION ALL
  SELECT epoch + 1, [theta[k] - {W3_MU} * ((list_dot_product(g[k], theta) - h[k]) / m + {workloads.LAMBDA} * theta[k]) FOR k IN range(1, 5)] FROM path, mat, vec, n WHERE epoch < {W3_EPOCHS})
SELECT epoch, round(theta[1], 4) AS price_r4, round(theta[2], 4) AS discount_r4, round(theta[3], 4) AS tax_r4, round(theta[4], 4) AS both_r4,
  round((list_dot_product(theta, [list_dot_product(line, theta) FOR line IN g]) - 2 * list_dot_product(theta, h) + yy) / (2 * m) + {workloads.LAMBDA / 2} * list_dot_product(theta, theta), 6) AS loss_r6
FROM path, mat, vec, n WHERE epoch % 10 = 0 AND epoch > 0""")
def w3_regression(spark, sf_dir):
    """W3: regression with known coefficients (1, -0.1, 0.1, -0.01) over nations of unequal size: padded lanes, alpha = 16, nine stragglers and more in every epoch."""
    ex = workloads.nation_examples(spark, sf_dir)
    g, h = moments.collect_moments(moments.device_moments(ex, 4, 1), D, 4, 1)
    m, squares = ex.agg(F.count("*"), F.sum(F.get("y", F.lit(0)) * F.get("y", F.lit(0)))).first()
    times = latency.np_epoch_times(latency.class_rates(D), W3_EPOCHS, latency.mac_count(latency.CODED, 4, 1), latency.message_bits(4, 1, 48), 7)
    note = lambda t: {"theta": t[:, 0].tolist(), "loss": moments.moment_loss(g, h, squares, m, t, workloads.LAMBDA)}
    r = train_coded(g, h, m, 16, times, workloads.LAMBDA, lambda e: W3_MU, evaluate=note, every=10)
    rows = [(t["epoch"], *t["theta"], t["loss"]) for t in r.trace if t["epoch"] % 10 == 0]
    names = ("price", "discount", "tax", "both")
    out = spark.createDataFrame(rows, "epoch int, price double, discount double, tax double, both double, loss double")
    return out.select("epoch", *[F.round(n, 4).alias(f"{n}_r4") for n in names], F.round("loss", 6).alias("loss_r6"))


_CHARS = """ch AS (SELECT doc_id, lang, unicode(unnest(string_split(text, ''))) % 64 AS bin FROM documents WHERE text <> '')"""


@query(f"WITH {_CHARS} SELECT lang, bin::INT AS bin, count(*) AS n FROM ch GROUP BY ALL")
def text_histogram(spark, sf_dir):
    h = text_histograms(read_table(spark, sf_dir, "documents", "lang", "text"), unit=False)
    cells = h.select("lang", F.posexplode("x").alias("bin", "v")).groupBy("lang", "bin").agg(F.sum("v").cast("long").alias("n"))
    return cells.where("n > 0")


def _rule(b: int, c: int) -> int:
    return (b * (c + 3) * 7 + c * 5) % 11 - 5


@query(f"""WITH {_CHARS}, cnt AS (SELECT doc_id, bin, count(*) AS n FROM ch GROUP BY ALL), cls AS (SELECT range AS c FROM range(4)),
s AS (SELECT doc_id, c, sum(n * ((bin * (c + 3) * 7 + c * 5) % 11 - 5)) AS v FROM cnt, cls GROUP BY ALL),
best AS (SELECT doc_id, arg_min(c, (-v, c)) AS predicted FROM s GROUP BY 1)
SELECT lang, count(*) AS n, sum((coalesce(predicted, 0) = list_position(['de', 'en', 'es', 'fr'], lang) - 1)::INT)::BIGINT AS hits FROM documents LEFT JOIN best USING (doc_id) GROUP BY 1""")
def predict_accuracy(spark, sf_dir):
    """Prediction and accuracy with a fixed integer model."""
    theta = np.array([[_rule(b, c) for c in range(4)] for b in range(64)], float)
    h = text_histograms(read_table(spark, sf_dir, "documents", "lang", "text"), unit=False)
    cls = F.array_position(F.array(*[F.lit(v) for v in workloads.LANGS]), F.col("lang")).cast("int") - 1
    return measures.accuracy(moments.predict(h, theta).withColumn("cls", cls), ["lang"])


_Q, _GAMMA = 8, 5.0


@query(f"""WITH w AS (SELECT q.range::INT AS q, i.range::INT AS i,
  sqrt(-2 * ln({o.uni("'rff'", "'w1'", 'q.range', 'i.range')})) * cos({2 * np.pi!r} * {o.uni("'rff'", "'w2'", 'q.range', 'i.range')}) * {float(np.sqrt(2 * _GAMMA))!r} AS w FROM range({_Q}) q, range(64) i),
s AS (SELECT vec_id, q, sum(embedding[i + 1]::DOUBLE * w) AS s FROM embeddings, w GROUP BY ALL)
SELECT vec_id, q, round({float(np.sqrt(2 / _Q))!r} * cos(s + {2 * np.pi!r} * {o.uni("'rff'", "'b'", 'q')}), 6) AS v_r6 FROM s""")
def rff_features(spark, sf_dir):
    t = read_table(spark, sf_dir, "embeddings", "vec_id", "embedding").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    return rbf_features_sql(t, 64, _Q, _GAMMA, "rff").select(F.col("id").alias("vec_id"), "q", F.round("v", 6).alias("v_r6"))


@query(SQL["rff_features"])
def rff_features_arrow(spark, sf_dir):
    """The same features in Arrow batches with one broadcast matrix."""
    t = read_table(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    return rbf_features(t, 64, _Q, _GAMMA, "rff").select("vec_id", F.posexplode("x").alias("q", "v")).select("vec_id", "q", F.round("v", 6).alias("v_r6"))


# --- latency ----------------------------------------------------------------------------------------

_LAT = "WITH " + o.latency(EPOCHS, RHO, BITS, LAT_SEED)


def _fleet(spark, sf_dir):
    return fleet_of(read_table(spark, sf_dir, "nation", "n_nationkey", "n_regionkey"))


def _latency(spark, sf_dir):
    return latency.sample(_fleet(spark, sf_dir), EPOCHS, RHO, BITS, LAT_SEED)


@query(_LAT + " SELECT epoch, device, class, round(comp_s, 6) AS comp_r6, round(setup_s, 6) AS setup_r6, round(up_s, 6) AS up_r6, round(down_s, 6) AS down_r6 FROM latency")
def latency_components(spark, sf_dir):
    return _latency(spark, sf_dir).select("epoch", "device", "class", *[F.round(f"{k}_s", 6).alias(f"{k}_r6") for k in ("comp", "setup", "up", "down")])


@query(_LAT + " SELECT epoch, device, place, round(total_s, 6) AS total_r6 FROM ranked WHERE place <= 3")
def kth_fastest(spark, sf_dir):
    return latency.fastest(_latency(spark, sf_dir), 3).select("epoch", "device", "place", F.round("total_s", 6).alias("total_r6"))


@query(_LAT + " SELECT epoch, round(max(total_s), 6) AS epoch_r6 FROM ranked WHERE place <= 10 GROUP BY 1")
def epoch_times(spark, sf_dir):
    return latency.epoch_time(_latency(spark, sf_dir), 10).select("epoch", F.round("seconds", 6).alias("epoch_r6"))


@query(_LAT + " SELECT epoch, device, class FROM ranked WHERE place <= 10")
def arrived_devices(spark, sf_dir):
    lat = _latency(spark, sf_dir)
    return lat.join(latency.fastest(lat, 10).select("epoch", "device"), ["epoch", "device"], "left_semi").select("epoch", "device", "class")


@query(_LAT + " SELECT epoch, device, class FROM ranked WHERE place > 10")
def stragglers(spark, sf_dir):
    lat = _latency(spark, sf_dir)
    return lat.join(latency.fastest(lat, 10).select("epoch", "device"), ["epoch", "device"], "left_anti").select("epoch", "device", "class")


@query(_LAT + " SELECT device, round(avg(total_s), 6) AS mean_r6 FROM latency GROUP BY 1 ORDER BY avg(total_s) DESC, device LIMIT 5")
def slowest_devices(spark, sf_dir):
    return _latency(spark, sf_dir).groupBy("device").agg(F.avg("total_s").alias("a")).orderBy(F.desc("a"), "device").limit(5).select("device", F.round("a", 6).alias("mean_r6"))


@query(_LAT + " SELECT class, device, count(*) AS n, round(avg(total_s), 6) AS mean_r6 FROM latency GROUP BY ROLLUP (class, device)")
def latency_rollup(spark, sf_dir):
    return _latency(spark, sf_dir).rollup("class", "device").agg(F.count("*").alias("n"), F.round(F.avg("total_s"), 6).alias("mean_r6"))


@query(_LAT + " SELECT class, round(quantile_cont(total_s, 0.5), 6) AS p50_r6, round(quantile_cont(total_s, 0.9), 6) AS p90_r6 FROM latency GROUP BY 1")
def latency_percentiles(spark, sf_dir):
    return _latency(spark, sf_dir).groupBy("class").agg(F.round(F.expr("percentile(total_s, 0.5)"), 6).alias("p50_r6"), F.round(F.expr("percentile(total_s, 0.9)"), 6).alias("p90_r6"))


def _sharing_sql() -> str:
    return f"WITH {o.fleet()}, s AS ({o.sharing_times(ALPHAS, 2000, 10, LAT_SEED)}) SELECT alpha, device, round(share_s, 5) AS share_r5, round(encode_s, 5) AS encode_r5 FROM s"


@query(_sharing_sql())
def sharing_time(spark, sf_dir):
    out = latency.sharing_phase(_fleet(spark, sf_dir), list(ALPHAS), 2000, 10, 48, LAT_SEED)
    return out.select("alpha", "device", F.round("share_s", 5).alias("share_r5"), F.round("encode_s", 5).alias("encode_r5"))


# --- traces and their measures ------------------------------------------------------------------------

TRACE_EPOCHS, KEEP = 60, 20
_TRACE = "WITH " + o.planted_trace(TRACE_EPOCHS, ALPHAS, KEEP, 6.0, workloads.LAMBDA, LAT_SEED)
TARGETS = (0.2, 0.3, 0.4, 0.45, 0.7)
_REACH = _TRACE + f""", reach AS (SELECT scheme, alpha, target, min(CASE WHEN accuracy >= target - 1e-9 THEN elapsed_s END) AS reached_s FROM trace, (SELECT unnest({list(TARGETS)}::DOUBLE[]) AS target) GROUP BY ALL)"""


def _trace(spark, sf_dir):
    return workloads.planted_trace(spark, sf_dir, TRACE_EPOCHS, ALPHAS, KEEP, LAT_SEED)


def _reached(trace, targets=TARGETS, by=("scheme", "alpha")):
    each = F.explode(F.array(*[F.lit(float(v)) for v in targets])).alias("target")
    return measures.time_to_accuracy(trace.select("*", each), F.col("target") - 1e-9, [*by, "target"])


@query(_TRACE + " SELECT scheme, alpha, epoch, round(loss, 5) AS loss_r5, round(accuracy, 5) AS accuracy_r5 FROM trace")
def planted_descent(spark, sf_dir):
    """Loss and test accuracy of each epoch: padded lanes with stragglers (alpha 6, 16, 23, 25) and baselines, against descent written out as a recursion."""
    return _trace(spark, sf_dir).select("scheme", "alpha", "epoch", F.round("loss", 5).alias("loss_r5"), F.round("accuracy", 5).alias("accuracy_r5"))


@query(_TRACE + " SELECT scheme, alpha, epoch, round(elapsed_s, 5) AS elapsed_r5 FROM trace")
def elapsed_time(spark, sf_dir):
    return _trace(spark, sf_dir).select("scheme", "alpha", "epoch", F.round("elapsed_s", 5).alias("elapsed_r5"))


@query(_REACH + " SELECT scheme, alpha, target, round(reached_s, 5) AS reached_r5 FROM reach")
def time_to_accuracy(spark, sf_dir):
    return _reached(_trace(spark, sf_dir)).select("scheme", "alpha", "target", F.round("reached_s", 5).alias("reached_r5"))


@query(_REACH + " SELECT a.target, a.alpha, round(b.reached_s / a.reached_s, 5) AS speedup_r5 FROM reach a JOIN reach b USING (target) WHERE a.scheme = 'coded' AND b.scheme = 'conventional'")
def speedup(spark, sf_dir):
    return measures.speedup(_reached(_trace(spark, sf_dir)), "coded", "conventional", ["target"]).select("target", "alpha", F.round("speedup", 5).alias("speedup_r5"))


@query(_REACH + " SELECT target, arg_min(alpha, (reached_s, alpha)) FILTER (reached_s IS NOT NULL) AS alpha, round(min(reached_s), 5) AS reached_r5 FROM reach WHERE scheme = 'coded' GROUP BY 1")
def best_alpha(spark, sf_dir):
    return measures.choose_alpha(_reached(_trace(spark, sf_dir)).where("scheme = 'coded'"), ["target"]).select("target", "alpha", F.round("reached_s", 5).alias("reached_r5"))


@query(_TRACE + " SELECT scheme, alpha, epoch, round(loss - lag(loss) OVER (PARTITION BY scheme, alpha ORDER BY epoch), 5) AS change_r5, round(avg(accuracy) OVER (PARTITION BY scheme, alpha ORDER BY epoch ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 5) AS mean3_r5 FROM trace")
def loss_delta(spark, sf_dir):
    w = Window.partitionBy("scheme", "alpha").orderBy("epoch")
    return _trace(spark, sf_dir).select("scheme", "alpha", "epoch", F.round(F.col("loss") - F.lag("loss").over(w), 5).alias("change_r5"), F.round(F.avg("accuracy").over(w.rowsBetween(-2, 0)), 5).alias("mean3_r5"))


@query(_LAT + " SELECT device FROM latency EXCEPT SELECT device FROM ranked WHERE place > 20")
def always_on_time(spark, sf_dir):
    lat = _latency(spark, sf_dir)
    on_time = latency.fastest(lat, 20).select("epoch", "device")
    late = lat.select("epoch", "device").exceptAll(on_time)
    return lat.select("device").distinct().exceptAll(late.select("device").distinct())


@query("""WITH e AS (SELECT max(len(embedding))::BIGINT AS raw, count(DISTINCT label)::BIGINT AS c, greatest(1, count(*) // 125)::BIGINT AS batch FROM embeddings), s AS (SELECT unnest([raw, 256, 2000]) AS d, c, batch FROM e)
SELECT 'coded' AS scheme, d, 1 AS alpha, d * d * c AS macs, d * c * 48 AS bits FROM s UNION ALL SELECT 'minibatch', d, 1, batch * 2 * d * c, d * c * 32 FROM s
UNION ALL SELECT 'encode', d, alpha, alpha * d * (d + c), (alpha - 1) * (d * (d + 1) // 2 + d * c) * 48 FROM s, (SELECT unnest([6, 16, 23, 25])::INT AS alpha)""")
def cost_table(spark, sf_dir):
    """Multiply-accumulates and bits of an epoch, and of the sharing phase for every alpha: embeddings as they come and under 256 and 2000 kernel features, five mini-batches on each of 25 devices."""
    t = read_table(spark, sf_dir, "embeddings", "embedding", "label")
    raw, c, n = t.agg(F.max(F.size("embedding")), F.count_distinct("label"), F.count("*")).first()
    batch, widths = max(1, n // (5 * D)), (raw, 256, 2000)
    rows = [(s, d, 1, latency.mac_count(s, d, c, batch), latency.message_bits(d, c, k)) for d in widths for s, k in (("coded", 48), ("minibatch", 32))]
    rows += [("encode", d, a, latency.mac_count("encode", d, c, alpha=a), sharing.share_bits(a, d, c, 48)) for d in widths for a in ALPHAS]
    return spark.createDataFrame(rows, "scheme string, d long, alpha int, macs long, bits long")


# --- baselines ----------------------------------------------------------------------------------------


@query(f"WITH {o.examples(D)}, r AS (SELECT vec_id, device, ((row_number() OVER (PARTITION BY device ORDER BY vec_id) - 1) % 5)::INT AS batch FROM ex) SELECT device, batch, count(*) AS n, min(vec_id) AS first_id FROM r GROUP BY ALL")
def minibatch_rows(spark, sf_dir):
    return _batched(spark, sf_dir).groupBy("device", "batch").agg(F.count("*").alias("n"), F.min("vec_id").alias("first_id"))


def _batched(spark, sf_dir):
    w = Window.partitionBy("device").orderBy("vec_id")
    return workloads.integer_examples(spark, sf_dir).withColumn("batch", ((F.row_number().over(w) - 1) % 5).cast("int"))


_DIAG = np.array([[0.5 if (i + j) % 2 else -0.25 for j in range(10)] for i in range(DIMS)])
_DIAG_SQL = "CASE WHEN (k.i + j) % 2 = 1 THEN 0.5 ELSE -0.25 END"


@query(f"""WITH {o.examples(D)}, b AS (SELECT vec_id, ((row_number() OVER (PARTITION BY device ORDER BY vec_id) - 1) % 5)::INT AS batch FROM ex),
pred AS (SELECT k.vec_id, j, sum(k.a * {_DIAG_SQL}) AS p FROM xs k, outs GROUP BY ALL),
res AS (SELECT vec_id, j, p - b AS r FROM pred JOIN ys USING (vec_id, j))
SELECT batch, x.i, j, sum(x.a * r)::DOUBLE AS v FROM xs x JOIN res USING (vec_id) JOIN b USING (vec_id) GROUP BY ALL""")
def minibatch_gradient(spark, sf_dir):
    """Mini-batch gradients from raw rows."""
    to = lambda c: F.transform(c, lambda v: v.cast("double"))
    rows = _batched(spark, sf_dir).select(F.col("batch").alias("device"), to("x").alias("x"), to("y").alias("y"))
    return moments.device_gradient_rows(rows, _DIAG).withColumnRenamed("device", "batch")


def _gradients_by_epoch(spark, sf_dir):
    g = moments.cross_cells(workloads.integer_examples(spark, sf_dir)).select("device", "i", "j", (-F.col("v")).alias("v"))
    n = workloads.integer_examples(spark, sf_dir).groupBy("device").agg(F.count("*").alias("rows"))
    kept = latency.fastest(_latency(spark, sf_dir).where("epoch <= 3"), 20).select("epoch", "device")
    return g, n, kept


@query(_LAT + f""", {o.examples(D)}, n AS (SELECT device, count(*) AS rows FROM ex GROUP BY 1), kept AS (SELECT epoch, device FROM ranked WHERE place <= 20 AND epoch <= 3),
m AS (SELECT epoch, sum(rows) AS m FROM kept JOIN n USING (device) GROUP BY 1)
SELECT epoch, i, j, round(sum(-v)::DOUBLE / any_value(m), 6) AS v_r6 FROM kept JOIN crs USING (device) JOIN m USING (epoch) GROUP BY epoch, i, j""")
def drop_slowest_gradient(spark, sf_dir):
    g, n, kept = _gradients_by_epoch(spark, sf_dir)
    m = kept.join(F.broadcast(n), "device").groupBy("epoch").agg(F.sum("rows").alias("m"))
    out = g.join(F.broadcast(kept), "device").groupBy("epoch", "i", "j").agg(F.sum("v").alias("v"))
    return out.join(F.broadcast(m), "epoch").select("epoch", "i", "j", F.round(F.col("v") / F.col("m"), 6).alias("v_r6"))


@query(_LAT + f""", {o.examples(D)}, n AS (SELECT device, count(*) AS rows FROM ex GROUP BY 1), kept AS (SELECT device FROM ranked WHERE place <= 20 AND epoch = 1),
sc AS (SELECT device, i, j, v / 16777216.0 AS h FROM crs), gs AS (SELECT device, i, j AS k, v / 16777216.0 AS g FROM gram),
one AS (SELECT device, i, j, h / rows AS t FROM sc JOIN n USING (device)),
two AS (SELECT o.device, o.i, o.j, any_value(o.t) - (sum(g.g * q.t) - any_value(s.h)) / any_value(n.rows) AS t FROM one o JOIN gs g ON g.device = o.device AND g.i = o.i JOIN one q ON q.device = o.device AND q.i = g.k AND q.j = o.j JOIN sc s ON s.device = o.device AND s.i = o.i AND s.j = o.j JOIN n ON n.device = o.device GROUP BY ALL)
SELECT i, j, round(sum(t * rows) / sum(rows), 6) AS v_r6 FROM two JOIN n USING (device) JOIN kept USING (device) GROUP BY ALL""")
def fedavg_round(spark, sf_dir):
    """One round of federated averaging: two local steps from zero on the 20 fastest devices."""
    rows = workloads.integer_examples(spark, sf_dir)
    to = lambda c: F.transform(c, lambda v: v.cast("double") / 4096)
    ex = rows.select("device", to("x").alias("x"), to("y").alias("y"))
    g, h = moments.collect_moments(moments.device_moments(ex, DIMS, 10), D, DIMS, 10)
    counts = np.zeros(D)
    for r in rows.groupBy("device").agg(F.count("*").alias("n")).collect():
        counts[r["device"]] = r["n"]
    lat = sorted((r["total_s"], r["device"]) for r in _latency(spark, sf_dir).where("epoch = 1").collect())
    times = np.zeros((1, D))
    for t, dev in lat:
        times[0, dev] = t
    theta = baselines.train_fedavg(g, h, counts, times, 20, local_steps=2, lam=0.0, mu=lambda e: 1.0).theta
    cells = [(i, j, float(theta[i, j])) for i in range(DIMS) for j in range(10)]
    return spark.createDataFrame(cells, "i int, j int, v double").select("i", "j", F.round("v", 6).alias("v_r6"))


@query(f"""WITH {o.examples(D)}, r AS (SELECT range::INT AS row FROM range(4)),
w AS (SELECT vec_id, row, sqrt((device % 5) / 5.0::DOUBLE) * sqrt(-2 * ln({o.uni("'parity'", "'a'", 'vec_id', 'row')})) * cos({2 * np.pi!r} * {o.uni("'parity'", "'b'", 'vec_id', 'row')}) AS w FROM ex, r)
SELECT row, i AS j, round(sum(w * a), 3) AS v_r3 FROM xs JOIN w USING (vec_id) GROUP BY ALL""")
def parity_rows(spark, sf_dir):
    """Four parity rows: random normal combinations of all examples, weighted by the chance of their device to be late."""
    rows = workloads.integer_examples(spark, sf_dir).withColumnRenamed("vec_id", "row_id")
    return baselines.parity_cells(rows, 4, (F.col("device") % 5) / F.lit(5.0)).select("row", "j", F.round("v", 3).alias("v_r3"))


@query("SELECT delta, ceil(delta * count(*)) / count(*) AS leaked FROM embeddings, (SELECT unnest([0.1, 0.8]::DOUBLE[]) AS delta) GROUP BY delta")
def parity_leakage(spark, sf_dir):
    m = read_table(spark, sf_dir, "embeddings", "vec_id").count()
    return spark.createDataFrame([(d, baselines.parity_leakage(d, m)) for d in (0.1, 0.8)], "delta double, leaked double")


@query("""WITH v AS (SELECT row_number() OVER (ORDER BY ts, event_id)::INT AS version, ts FROM events WHERE event_id % 50 = 0)
SELECT e.event_id, (e.user_id % 25)::INT AS device, max(v.version)::INT AS version FROM events e LEFT JOIN v ON v.ts <= e.ts GROUP BY ALL""")
def model_asof_arrival(spark, sf_dir):
    """The last model version that was there when an answer arrived: an as-of join by a running maximum within days, carried over day by day."""
    ev = read_table(spark, sf_dir, "events", "event_id", "ts", "user_id")
    versions = ev.where(F.col("event_id") % 50 == 0).select("ts", "event_id")
    day = F.date_trunc("DAY", "ts")
    counts = versions.groupBy(day.alias("day")).agg(F.count("*").alias("n"))
    days = ev.select(day.alias("day")).distinct().join(counts, "day", "left")
    before = F.coalesce(F.sum("n").over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    days = days.select("day", before.alias("before"))
    marks = versions.select("ts", "event_id", F.lit(1).alias("mark"), F.lit(None).cast("int").alias("device"))
    rows = ev.select("ts", "event_id", F.lit(0).alias("mark"), F.pmod("user_id", F.lit(25)).cast("int").alias("device")).unionByName(marks).withColumn("day", day)
    seen = F.sum("mark").over(Window.partitionBy("day").orderBy(F.col("ts").asc()).rangeBetween(Window.unboundedPreceding, Window.currentRow))
    out = rows.withColumn("seen", seen).where("mark = 0").join(F.broadcast(days), "day")
    version = F.col("before") + F.col("seen")
    return out.select("event_id", "device", F.when(version > 0, version).cast("int").alias("version"))


# --- surrounding operators -------------------------------------------------------------------------------


@query("SELECT label::INT AS label, count(*) AS n, round(avg(embedding[1]::DOUBLE), 6) AS mean_r6 FROM embeddings WHERE label < 5 GROUP BY 1")
def scan_embeddings(spark, sf_dir):
    t = read_table(spark, sf_dir, "embeddings", "label", "embedding").where("label < 5")
    return t.groupBy(F.col("label").cast("int").alias("label")).agg(F.count("*").alias("n"), F.round(F.avg(F.get("embedding", F.lit(0)).cast("double")), 6).alias("mean_r6"))


@query(f"WITH {o.examples(D)} SELECT device, count(*) AS n, sum(a)::BIGINT AS total FROM xs WHERE device IN (3, 7) GROUP BY 1")
def sink_roundtrip(spark, sf_dir):
    """Written by device and read back for two devices: only their folders are read."""
    from padgrad.shared import fresh_path

    path = fresh_path(spark, "by-device")
    write_by_device(workloads.integer_examples(spark, sf_dir).select("device", "vec_id", "x"), path)
    t = spark.read.parquet(path).where(F.col("device").isin(3, 7)).select("device", F.explode("x").alias("a"))
    return t.groupBy(F.col("device").cast("int").alias("device")).agg(F.count("*").alias("n"), F.sum("a").alias("total"))


@query("SELECT quality, toxic, count(*) AS n FROM labels GROUP BY CUBE (quality, toxic)")
def label_cube(spark, sf_dir):
    return read_table(spark, sf_dir, "labels", "quality", "toxic").cube("quality", "toxic").agg(F.count("*").alias("n"))


@query("SELECT event_type, json_extract_string(props, '$.k') AS k, count(*) AS n FROM events GROUP BY ALL")
def props_k(spark, sf_dir):
    return read_table(spark, sf_dir, "events", "event_type", "props").groupBy("event_type", F.get_json_object("props", "$.k").alias("k")).agg(F.count("*").alias("n"))


@query("SELECT date_trunc('day', ts)::DATE AS day, (user_id % 25)::INT AS device, count(*) AS n FROM events GROUP BY ALL")
def epoch_of_event(spark, sf_dir):
    t = read_table(spark, sf_dir, "events", "ts", "user_id")
    return t.groupBy(F.date_trunc("DAY", "ts").cast("date").alias("day"), F.pmod("user_id", F.lit(25)).cast("int").alias("device")).agg(F.count("*").alias("n"))


@query("SELECT vec_id, round(list_sum([v::DOUBLE * v::DOUBLE FOR v IN embedding]), 5) AS norm_r5, (list_position(embedding[1:10], list_max(embedding[1:10])) - 1)::INT AS cls FROM embeddings")
def array_dot(spark, sf_dir):
    x = F.transform("embedding", lambda v: v.cast("double"))
    return read_table(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", F.round(dot(x, x), 5).alias("norm_r5"), argmax(F.slice("embedding", 1, 10)).alias("cls"))


@query("SELECT s_nationkey::INT AS device, count(*) AS suppliers, round(sum(s_acctbal), 2) AS balance FROM supplier GROUP BY 1")
def suppliers_by_device(spark, sf_dir):
    return read_table(spark, sf_dir, "supplier", "s_nationkey", "s_acctbal").groupBy(F.col("s_nationkey").cast("int").alias("device")).agg(F.count("*").alias("suppliers"), F.round(F.sum("s_acctbal"), 2).alias("balance"))


# --- streams ------------------------------------------------------------------------------------------------


@query("SELECT date_trunc('day', ts)::VARCHAR AS epoch, (user_id % 25)::INT AS device, count(*) AS n FROM events WHERE ts < (SELECT max(ts) - INTERVAL 1 HOUR FROM events) AND date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY ALL")
def stream_epoch_counts(spark, sf_dir):
    """Counts of the epochs that the watermark has closed."""
    out = arrivals.run_available(arrivals.epoch_counts(arrivals.event_stream(spark, sf_dir)))
    return out.select(F.date_format("epoch", "yyyy-MM-dd HH:mm:ss").alias("epoch"), "device", "n")


_FIRST = """WITH a AS (SELECT date_trunc('day', ts) AS epoch, (user_id % 25)::INT AS device, min((ts, event_id)) AS f FROM events GROUP BY 1, 2),
r AS (SELECT *, row_number() OVER (PARTITION BY epoch ORDER BY f, device)::INT AS place, count(*) OVER (PARTITION BY epoch) AS got FROM a)"""


@query(_FIRST + " SELECT epoch::VARCHAR AS epoch, device, place FROM r WHERE place <= 10 AND got >= 10")
def first_answers(spark, sf_dir):
    out = arrivals.first_answers_batch(read_table(spark, sf_dir, "events"), 10)
    return out.select(F.date_format("epoch", "yyyy-MM-dd HH:mm:ss").alias("epoch"), "device", "place")


@query(_FIRST + " SELECT epoch::VARCHAR AS epoch, device, place FROM r WHERE place <= 10 AND got >= 10 AND epoch + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)")
def stream_first_k(spark, sf_dir):
    out = arrivals.run_available(arrivals.first_answers(arrivals.event_stream(spark, sf_dir), 10))
    return out.select(F.date_format("epoch", "yyyy-MM-dd HH:mm:ss").alias("epoch"), "device", "place")


@query(_FIRST + " SELECT epoch::VARCHAR AS epoch, device FROM r WHERE place > 10")
def stream_late_devices(spark, sf_dir):
    ev = read_table(spark, sf_dir, "events")
    out = arrivals.late_devices(ev, arrivals.first_answers_batch(ev, 10))
    return out.select(F.date_format("epoch", "yyyy-MM-dd HH:mm:ss").alias("epoch"), "device")


@query("""WITH s AS (SELECT range AS k FROM range(31)), w AS (SELECT min(date_trunc('day', ts)) AS d0 FROM events),
st AS (SELECT d0 + to_days((k - 1)::INT) AS start FROM s, w, (SELECT 1))
SELECT start::VARCHAR AS start, count(*) AS n FROM st JOIN events ON ts >= start AND ts < start + INTERVAL 2 DAY GROUP BY 1""")
def sliding_counts(spark, sf_dir):
    out = arrivals.sliding_counts(read_table(spark, sf_dir, "events", "ts", "user_id"))
    return out.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query("""WITH a AS (SELECT (user_id % 25)::INT AS device, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id % 25 ORDER BY ts, event_id) < INTERVAL 1 HOUR THEN 0 ELSE 1 END AS opens FROM events),
r AS (SELECT device, ts, sum(opens) OVER (PARTITION BY device ORDER BY ts, event_id) AS run FROM a)
SELECT device, count(*) AS sessions, sum(n)::BIGINT AS answers, max(n) AS longest FROM (SELECT device, run, count(*) AS n FROM r GROUP BY ALL) GROUP BY 1""")
def device_sessions(spark, sf_dir):
    s = arrivals.sessions(read_table(spark, sf_dir, "events", "ts", "user_id"))
    return s.groupBy("device").agg(F.count("*").alias("sessions"), F.sum("n").alias("answers"), F.max("n").alias("longest"))


@query("SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY 1")
def stream_once(spark, sf_dir):
    """A stream in which every answer is counted once."""
    out = arrivals.run_available(arrivals.once(arrivals.event_stream(spark, sf_dir)).select("event_type"))
    return out.groupBy("event_type").agg(F.count("*").alias("n"))


@query("SELECT date_trunc('day', ts)::VARCHAR AS epoch, (user_id % 25)::INT AS device, count(*) AS n FROM events WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY ALL")
def stream_drops_late(spark, sf_dir):
    """Answers sent again behind the watermark come after the stream has stopped once, and change nothing."""
    out = arrivals.run_with_late_copies(spark, read_table(spark, sf_dir, "events"), arrivals.epoch_counts)
    return out.select(F.date_format("epoch", "yyyy-MM-dd HH:mm:ss").alias("epoch"), "device", "n")


@query("SELECT date_trunc('day', ts)::VARCHAR AS epoch, greatest(n_regionkey - 1, 0)::INT AS class, count(*) AS n FROM events JOIN nation ON n_nationkey = user_id % 25 WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY ALL")
def stream_class_counts(spark, sf_dir):
    """A stream joined with the table of devices: answers of each class in closed epochs."""
    out = arrivals.run_available(arrivals.epoch_counts(arrivals.event_stream(spark, sf_dir)).join(F.broadcast(_fleet(spark, sf_dir).select("device", "class")), "device"))
    return out.groupBy(F.date_format("epoch", "yyyy-MM-dd HH:mm:ss").alias("epoch"), "class").agg(F.sum("n").alias("n"))


@query("""WITH s AS (SELECT range AS k FROM range(31)), w AS (SELECT min(date_trunc('day', ts)) AS d0, max(ts) - INTERVAL 1 HOUR AS mark FROM events),
st AS (SELECT d0 + to_days((k - 1)::INT) AS start, mark FROM s, w)
SELECT start::VARCHAR AS start, count(*) AS n FROM st JOIN events ON ts >= start AND ts < start + INTERVAL 2 DAY WHERE start + INTERVAL 2 DAY <= mark GROUP BY 1""")
def stream_sliding(spark, sf_dir):
    """Overlapping windows as a stream: those that the watermark has closed."""
    out = arrivals.run_available(arrivals.sliding_counts(arrivals.event_stream(spark, sf_dir)))
    return out.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query("""WITH a AS (SELECT (user_id % 25)::INT AS device, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id % 25 ORDER BY ts, event_id) < INTERVAL 1 HOUR THEN 0 ELSE 1 END AS opens FROM events),
r AS (SELECT device, ts, sum(opens) OVER (PARTITION BY device ORDER BY ts, event_id) AS run FROM a)
SELECT device, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS first_ts, count(*) AS n FROM r GROUP BY device, run HAVING max(ts) + INTERVAL 1 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)""")
def stream_sessions(spark, sf_dir):
    """Sessions of devices as a stream: those that the watermark has closed."""
    out = arrivals.run_available(arrivals.sessions(arrivals.event_stream(spark, sf_dir)))
    return out.select("device", F.date_format("first_ts", "yyyy-MM-dd HH:mm:ss").alias("first_ts"), "n")


@query("""WITH c AS (SELECT a.range AS a, b.range AS b, c.range AS c FROM range(5) a, range(5) b, range(5) c WHERE a.range < b.range AND b.range < c.range),
p AS (SELECT row_number() OVER (ORDER BY a, b, c) - 1 AS pattern_id, [a, b, c] AS s FROM c) SELECT pattern_id, unnest(s)::INT AS device FROM p""")
def patterns(spark, sf_dir):
    return gradcode.pattern_rows(spark, read_table(spark, sf_dir, "region", "r_regionkey").count(), ALPHA5)


def _fleet_sql() -> str:
    u = lambda kind: o.uni("'1'", "epoch", "device", repr(kind))
    return f"""WITH f AS (SELECT e.range AS epoch, d.range AS device, CASE WHEN d.range < 10 THEN 25e6 WHEN d.range < 15 THEN 5e6 WHEN d.range < 20 THEN 2.5e6 ELSE 1.25e6 END::DOUBLE AS tau FROM range(1, 101) e, range(25) d)
SELECT epoch::INT AS epoch, device::INT AS device, round(4e7 / tau * (1 - ln({u('setup')}) / 2) + greatest(1, ceil(ln({u('up')}) / ln(0.1))) * 1056000.0 / 5e6 + greatest(1, ceil(ln({u('down')}) / ln(0.1))) * 1056000.0 / 10e6, 5) AS total_r5 FROM f"""


@query(_fleet_sql())
def simulated_fleet(spark, sf_dir):
    """The simulated fleet read through its data source."""
    from padgrad.sources.fleet_source import register

    register(spark)
    return spark.read.format("simulated_fleet").load().select("epoch", "device", F.round("total_s", 5).alias("total_r5"))


# --- other sources -----------------------------------------------------------------------------------------------


@query("WITH t AS (SELECT regexp_replace(html, '<[^>]*>', ' ', 'g') AS text FROM pages), ch AS (SELECT unicode(unnest(string_split(text, ''))) % 64 AS bin FROM t WHERE text <> '') SELECT bin::INT AS bin, count(*) AS n FROM ch GROUP BY 1")
def page_histogram(spark, sf_dir):
    """Histogram of the characters of all pages without their tags."""
    t = read_table(spark, sf_dir, "pages", "html").select(F.regexp_replace("html", "<[^>]*>", " ").alias("text"))
    return text_histograms(t, unit=False).select(F.posexplode("x").alias("bin", "v")).groupBy("bin").agg(F.sum("v").cast("long").alias("n")).where("n > 0")


@query("WITH ch AS (SELECT role, unicode(unnest(string_split(text, ''))) % 64 AS bin FROM conversations WHERE text <> '') SELECT role, bin::INT AS bin, count(*) AS n FROM ch GROUP BY ALL")
def role_histogram(spark, sf_dir):
    t = read_table(spark, sf_dir, "conversations", "role", "text")
    return text_histograms(t, unit=False).select("role", F.posexplode("x").alias("bin", "v")).groupBy("role", "bin").agg(F.sum("v").cast("long").alias("n")).where("n > 0")


@query("""WITH ch AS (SELECT item_id, unicode(unnest(string_split(text, ''))) % 64 AS bin FROM benchmark WHERE text <> ''), cnt AS (SELECT item_id, bin, count(*) AS n FROM ch GROUP BY ALL), cls AS (SELECT range AS c FROM range(4)),
s AS (SELECT item_id, c, sum(n * ((bin * (c + 3) * 7 + c * 5) % 11 - 5)) AS v FROM cnt, cls GROUP BY ALL) SELECT item_id, arg_min(c, (-v, c))::INT AS predicted FROM s GROUP BY 1""")
def benchmark_predictions(spark, sf_dir):
    """The fixed integer model on benchmark items."""
    theta = np.array([[_rule(b, c) for c in range(4)] for b in range(64)], float)
    h = text_histograms(read_table(spark, sf_dir, "benchmark", "item_id", "text"), unit=False)
    return moments.predict(h, theta).select("item_id", "predicted")


@query("SELECT (p_partkey % 25)::INT AS device, count(*) AS parts, sum(p_size)::BIGINT AS size, round(max(p_retailprice), 2) AS top_price FROM part GROUP BY 1")
def parts_by_device(spark, sf_dir):
    t = read_table(spark, sf_dir, "part", "p_partkey", "p_size", "p_retailprice")
    return t.groupBy(F.pmod("p_partkey", F.lit(25)).cast("int").alias("device")).agg(F.count("*").alias("parts"), F.sum("p_size").cast("long").alias("size"), F.round(F.max("p_retailprice"), 2).alias("top_price"))


@query()
def w7_unlearnable_labels(spark, sf_dir):
    """Noise control: on labels that cannot be learned all exact schemes still agree (largest difference of their models)."""
    rows = read_table(spark, sf_dir, "embeddings", "vec_id", "embedding", "label")
    x = F.transform("embedding", lambda v: v.cast("double"))
    ex = rows.select(F.col("vec_id").alias("row_id"), x.alias("x"), F.col("label").cast("int").alias("cls"), F.lit(False).alias("is_test"))
    ex = ex.withColumn("y", F.transform(F.sequence(F.lit(0), F.lit(9)), lambda k: (k == F.col("cls")).cast("double")))
    w = workloads.Workload(workloads._split(ex, "sorted"), 64, 10)
    times = latency.np_epoch_times(w.rates, 60, 1e6, 1e4, 2)
    base = baselines.train_central(w.g, w.h, w.m, 60, workloads.LAMBDA, w.mu).theta
    out = [(a, float(np.abs(train_coded(w.g, w.h, w.m, a, times, workloads.LAMBDA, w.mu).theta - base).max())) for a in (1, *ALPHAS)]
    return spark.createDataFrame(out, "alpha int, largest_difference double")


@query()
def literal_hazard(spark, sf_dir):
    """How often shares wrap, and coded shares wrap apart from their pads, in the published arithmetic and how wrong models get, against exact lanes: narrow types (32, 16) and the published ones (48, 24), 30 epochs of W1. ``left_type_at``: the epoch whose model no longer fits the type."""
    ex, d, c = workloads.planted_examples(spark, sf_dir)
    w = workloads.Workload(ex, d, c)
    times = latency.np_epoch_times(w.rates, 30, 1e6, 1e4, 2)
    base = baselines.train_central(w.g, w.h, w.m, 30, workloads.LAMBDA, w.mu).theta
    out = []
    for k, f in ((32, 16), (48, 24)):
        for a in ALPHAS:
            for mode in ("literal", "lifted"):
                r = train_coded(w.g, w.h, w.m, a, times, workloads.LAMBDA, w.mu, mode=mode, k=k, f=f)
                out.append((k, f, a, mode, r.notes["wraps"], r.notes["coded_wraps"], float(np.abs(r.theta - base).max()), r.notes.get("left_type_at")))
    return spark.createDataFrame(out, "k int, f int, alpha int, mode string, wraps long, coded_wraps long, largest_difference double, left_type_at int")


# --- workloads -------------------------------------------------------------------------------------------------


def _curves(spark, sf_dir, name, examples, **options):
    def make():
        ex, d, c = examples(spark, sf_dir)
        return workloads.trace_table(spark, workloads.Workload(ex, d, c).curves(**options))

    return workloads.kept_table(spark, (name, sf_dir), make)


@query()
def w1_curves(spark, sf_dir):
    """Planted classes of embeddings: traces of all schemes."""
    return _curves(spark, sf_dir, "w1", workloads.planted_examples, epochs=200)


@query()
def w2_curves(spark, sf_dir):
    """Language of documents under kernel features: traces of all schemes."""
    return _curves(spark, sf_dir, "w2", workloads.language_examples, epochs=400)


@query()
def w4_curves(spark, sf_dir):
    """Quality of documents, a skewed binary label: the padded scheme for every alpha and baselines."""
    return _curves(spark, sf_dir, "w4", workloads.quality_examples, epochs=200)


@query()
def w11_role_curves(spark, sf_dir):
    """Who speaks in a conversation, from its characters: the padded scheme and baselines."""
    return _curves(spark, sf_dir, "w11", workloads.role_examples, epochs=100, alphas=(16, 23), deltas=(0.1,))


@query()
def w8_target_sweep(spark, sf_dir):
    """Seconds to each target accuracy on the language workload, for every scheme, and how many times faster than conventional mini-batches."""
    reached = _reached(w2_curves(spark, sf_dir), (0.9, 0.95, 0.97, 0.98, 0.985, 0.99), ("scheme", "alpha", "mode", "bits"))
    base = reached.where("scheme = 'conventional'").select("target", F.col("reached_s").alias("base_s"))
    return reached.join(F.broadcast(base), "target").withColumn("speedup", F.col("base_s") / F.col("reached_s"))


@query()
def w10_scaling(spark, sf_dir):
    """Cost of the moment pass, the sharing phase on tables and one epoch as features and devices grow; rows are those of the scale factor."""
    rows = []
    for q, devices in ((64, 5), (64, 25), (64, 100), (128, 25), (256, 25)):
        docs = rbf_features(workloads.language_rows(spark, sf_dir), 64, q).withColumn("device", F.pmod(F.xxhash64("row_id"), F.lit(devices)).cast("int"))
        m = moments.device_moments(docs.select("device", "x", "y"), q, 4)
        kept = []
        steps = [measures.engine_measures(spark, "moments", lambda m=m: kept.append(written(m, "scaling")))]
        alpha = devices - 2
        steps.append(measures.engine_measures(spark, "sharing", lambda: kept.append(CodedTables(kept[0], devices, alpha, (q, 4), SEED))))
        steps.append(measures.engine_measures(spark, "epoch", lambda: kept[1].gradient_sum(np.zeros((q, 4)), range(devices))))
        kept[1].drop()
        rows += [(devices, q, s["step"], s["wall_s"], s["tasks"], s["task_s"], s["input_mb"], s["shuffle_mb"]) for s in steps]
    return spark.createDataFrame(rows, "devices int, features int, step string, wall_s double, tasks int, task_s double, input_mb double, shuffle_mb double")


@query()
def w9_split_contrast(spark, sf_dir):
    """Dropping the slowest on a label-sorted and on an iid split."""
    rows = []
    for split in ("sorted", "hash"):
        ex, d, c = workloads.language_examples(spark, sf_dir, q=128, split=split)
        w = workloads.Workload(ex, d, c)
        rows += [{**r, "scheme": f"{r['scheme']}_{split}"} for r in w.curves(epochs=100, alphas=ALPHAS, deltas=(), literal_epochs=20) if r["scheme"] in ("coded", "drop_slowest", "fedavg")]
    return workloads.trace_table(spark, rows)


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Flagship: coded descent in padded lanes on W1 with alpha = 23, trace rows."""
    ex, d, c = workloads.planted_examples(spark, sf_dir)
    w = workloads.Workload(ex, d, c)
    times = latency.np_epoch_times(w.rates, 10, latency.mac_count("coded", d, c), latency.message_bits(d, c, 48), 1)
    r = train_coded(w.g, w.h, w.m, 23, times, workloads.LAMBDA, w.mu, evaluate=lambda t: {"theta": t.copy()})
    return workloads.trace_table(spark, w.traced({("coded", 23, "lifted", 48): r}))


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
