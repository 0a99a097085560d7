"""Bounds, lattices, roundings, codec, draws and ledgers as queries."""

from __future__ import annotations

from pyspark.sql import functions as F

from fewbit.functions import theory as th
from fewbit.functions.codec import bit_text_sql, pack_udf, unpack_udf
from fewbit.functions.lattice import Lattice, round_sql
from fewbit.functions.ledger import bits_sql, compression
from fewbit.functions.rng import duck_uniform, spark_uniform
from fewbit.plans.methods import METHODS
from fewbit.sources import load

L, MU, DIM = 0.967, 0.2, 9
TARGETS = (0.2, 0.5, 0.9, 0.99)
FIGURE_NOISE = 0.954


def _grid(spark, name, values, kind):
    return spark.createDataFrame([(v,) for v in values], f"{name} {kind}")


#: Settings that a line item stands for: a target, a step, bits, a dimension and a number of steps from its columns. SQL for Spark and DuckDB alike.
OF_ITEM = {
    "target": "CAST(l_linenumber AS DOUBLE) / 8",
    "a": "CAST(l_quantity AS DOUBLE) / 400",
    "p": "CAST(8 + round(100 * l_tax) AS INTEGER)",
    "d": "CAST(l_quantity AS BIGINT)",
    "t": "CAST(l_linenumber AS BIGINT)",
}


def _items_sql(**columns: str) -> str:
    """Distinct settings of all line items with the number of items that have them, as `items`."""
    return f"SELECT {', '.join(f'{v} AS {k}' for k, v in columns.items())}, count(*) AS items FROM lineitem GROUP BY ALL"


def _items(spark, sf_dir, **columns: str):
    return load(spark, sf_dir, "lineitem").select(*[F.expr(v).alias(k) for k, v in columns.items()]).groupBy(*columns).agg(F.count("*").alias("items"))


def _of(*names: str) -> dict[str, str]:
    return {n: OF_ITEM[n] for n in names}


def epoch_by_step(spark, sf_dir):
    """Least epoch length over the items' steps, targets and bits."""
    return _items(spark, sf_dir, **_of("target", "p", "a")).select("target", "p", "a", "items", F.round(F.expr(th.epoch_sql("target", str(L), str(MU), "a", str(DIM), "p")), 4).alias("t_min"))


def _epoch_by_bits(noise):
    def query(spark, sf_dir):
        grid = _grid(spark, "target", TARGETS, "double").crossJoin(spark.range(8, 33).select(F.col("id").cast("int").alias("p")))
        best = grid.withColumn("a", F.expr(th.best_step_sql("target", str(L), str(MU), str(DIM), "p", noise)))
        return best.select("target", "p", F.ceil(F.expr(th.epoch_sql("target", str(L), str(MU), "a", str(DIM), "p", noise))).cast("long").alias("t_min"))

    return query


BY_BITS = {**_of("target"), "p": "CAST(8 + l_quantity % 25 AS INTEGER)"}


def epoch_by_items_bits(spark, sf_dir):
    """The same over the targets of the line items and 8 to 32 bits by their quantities."""
    best = _items(spark, sf_dir, **BY_BITS).withColumn("a", F.expr(th.best_step_sql("target", str(L), str(MU), str(DIM), "p")))
    return best.select("target", "p", "items", F.ceil(F.expr(th.epoch_sql("target", str(L), str(MU), "a", str(DIM), "p"))).cast("long").alias("t_min"))


def bits_by_dimension(spark, sf_dir):
    """Bits per coordinate that a contraction needs, by dimension."""
    rows = [(d, int(th.adaptive_bits_min(L, MU, 0.05, d))) for d in (10, 32, 100, 316, 1000)]
    return spark.createDataFrame(rows, "d int, p_min int")


LONG = 400


def bounds(spark, sf_dir):
    """All bound functions at the items' steps and bits; null where no epoch length or number of bits does."""

    @F.udf("fixed_epoch double, fixed_rate double, bits double, epoch double, rate double")
    def made(a, p):
        all_five = th.fixed_epoch_min(L, MU, a), th.fixed_rate(L, MU, a, LONG), th.adaptive_bits_min(L, MU, a, DIM), th.adaptive_epoch_min(L, MU, a, DIM, p), th.adaptive_rate(L, MU, a, DIM, p, LONG)
        return tuple(None if v == float("inf") else round(float(v), 6) for v in all_five)

    return _items(spark, sf_dir, **_of("a", "p")).withColumn("b", made("a", "p")).select("a", "p", "items", "b.*")


def step_windows(spark, sf_dir):
    """Feasible and best steps by target and bits; null where there are none."""

    @F.udf("low double, high double, best double")
    def made(target, p):
        window = th.step_window(target, L, MU, DIM, p)
        return *(None if v != v else round(v, 9) for v in window), round(th.best_step(target, L, MU, DIM, p), 9)

    return _items(spark, sf_dir, **_of("target", "p")).withColumn("b", made("target", "p")).select("target", "p", "items", "b.*")


def targets(spark, sf_dir):
    """Bits and epoch length for a wanted contraction, and the rounding variance cap."""

    @F.udf("a double, bits int, epoch double, variance_cap double, grad_radius double, step_limit double, ball double")
    def made(target):
        a = th.best_step(target, L, MU, DIM, 15)
        own = th.epoch_for_target(target, L, MU, a, DIM, 15), th.rounding_variance_cap(th.model_radius(1.0, MU), 15, DIM), th.grad_radius(1.0, L, MU), th.step_limit(L), th.fixed_ball(L, MU, 0.1, LONG, 1e-4, [1e-4] * 8)
        return round(a, 9), int(th.bits_for_target(target, L, MU, a, DIM)), *(round(v, 9) for v in own)

    return _items(spark, sf_dir, **_of("target")).withColumn("b", made("target")).select("target", "items", "b.*")


def uniforms(spark, sf_dir):
    """Draws of worker and step by key, a round an event."""
    keys = load(spark, sf_dir, "events").select(F.col("event_id").alias("k"))
    u = F.expr(spark_uniform("concat('42|worker|', k, '|1|0')"))
    v = F.expr(spark_uniform("concat('42|pick|', k, '|0|0')"))
    return keys.select("k", u.alias("u"), F.floor(u * 10).cast("int").alias("worker"), F.floor(v * 8).cast("int").alias("step"))


def _cells(spark, sf_dir):
    e = load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("dim", "v"))
    return e.select("vec_id", "dim", F.col("v").cast("double").alias("v"))


def _rounding(u_spark):
    def query(spark, sf_dir):
        u = spark_uniform("concat('7|model|1|', vec_id, '|', dim)") if u_spark else "0.5D"
        out = _cells(spark, sf_dir).withColumn("q", F.expr(round_sql("v", "0.0D", "0.25D", "4.0D", u)))
        return out.select("vec_id", "dim", F.round("q", 9).alias("q"), (F.abs("v") > 0.25).alias("saturated"))

    return query


LATTICES = {**_of("target"), "p": f"1 + ({OF_ITEM['p']}) % 6"}


def lattice_points(spark, sf_dir):
    """The points of lattices of one coordinate with 1 to 6 bits around the items' targets, both ends included."""
    points = F.udf(lambda c, p: [round(float(v), 9) for v in Lattice.of([c], 1.0, p).points(0)], "array<double>")
    return _items(spark, sf_dir, **LATTICES).select("target", "p", "items", F.posexplode(points("target", "p")).alias("j", "point"))


def cell_join(spark, sf_dir):
    """Coordinate to lattice cell by a range join against the cells, the plain form of the rounding's position.

    The outer cells are open, as the rounding clamps to the ends of the lattice. A null coordinate has no cell.
    """
    end = lambda i, edge, sign: F.when(F.col("id") == edge, float(f"{sign}inf")).otherwise(-0.25 + i * (0.5 / 15))
    cells = spark.range(0, 15).select(F.col("id").cast("int").alias("cell"), end(F.col("id"), 0, "-").alias("lo"), end(F.col("id") + 1, 14, "").alias("hi"))
    v = _cells(spark, sf_dir)
    hit = v.join(F.broadcast(cells), (v.v >= cells.lo) & ((v.v < cells.hi) | (cells.hi == float("inf"))), "left")
    return hit.groupBy("dim", "cell").agg(F.count("*").alias("n"))


ITEM_KEY = "concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey)"
ITEM_VALUE = "(CAST(l_quantity AS DOUBLE) - 25.5) / 24.5"


def unbiased(spark, sf_dir):
    """Bias and largest error of roundings of the items' scaled quantities, one draw an item, beside their number."""
    items = load(spark, sf_dir, "lineitem").select(F.expr(ITEM_KEY).alias("s"), F.expr(ITEM_VALUE).alias("v"))
    q = items.withColumn("q", F.expr(round_sql("v", "0.0D", "1.0D", "3.0D", spark_uniform("concat(s, '|model|1|1')"))))
    return q.groupBy(F.round("v", 9).alias("v")).agg(F.count("*").alias("n"), F.round(F.abs(F.avg("q") - F.first("v")), 9).alias("abs_bias"), F.round(F.max(F.abs(F.col("q") - F.col("v"))), 9).alias("max_err"), F.round(F.avg((F.col("q") - F.col("v")) ** 2), 9).alias("mse"))


def bias_by_coordinate(spark, sf_dir):
    """The same over the vectors: every coordinate of every vector, 16 roundings each, summed up by coordinate."""
    runs = _cells(spark, sf_dir).crossJoin(F.broadcast(spark.range(16).withColumnRenamed("id", "s")))
    kept = runs.withColumn("v", F.greatest(F.least("v", F.lit(0.25)), F.lit(-0.25)))
    q = kept.withColumn("e", F.expr(round_sql("v", "0.0D", "0.25D", "4.0D", spark_uniform("concat(s, '|model|2|', vec_id, '|', dim)"))) - F.col("v"))
    return q.groupBy("dim").agg(F.round(F.avg("e"), 9).alias("bias"), F.round(F.max(F.abs("e")), 9).alias("max_err"), F.round(F.avg(F.col("e") ** 2), 9).alias("mse"), F.count("e").alias("n"))


def codec_round_trip(spark, sf_dir):
    """Vectors as packed messages and back: sizes in bytes and whether every index came back."""
    e = load(spark, sf_dir, "embeddings")
    index = e.select("vec_id", F.expr("transform(embedding, v -> bigint(floor(greatest(least((v + 0.5) * 31, 31), 0))))").alias("i"))
    made = index.withColumn("m", pack_udf(5)("i")).withColumn("back", unpack_udf(5, 64)("m"))
    return made.select("vec_id", F.octet_length("m").alias("bytes"), (F.col("i") == F.col("back")).alias("same"), F.expr("left(array_join(transform(i, x -> " + bit_text_sql("x", 5) + "), ''), 10)").alias("head"))


LEDGER = {**_of("d"), "n": "10::BIGINT", **_of("t"), "p": f"CAST({OF_ITEM['p']} AS BIGINT)"}


def ledger(spark, sf_dir):
    """Bits of an iteration of every method, at the settings of the line items."""
    t = _items(spark, sf_dir, **LEDGER).crossJoin(F.broadcast(_grid(spark, "method", METHODS, "string")))
    return t.select("method", "d", "n", "t", "p", "items", F.expr(bits_sql("d", "n", "t", "(p * d)", "(p * d)")).alias("bits"))


def compressed(spark, sf_dir):
    """Saved share of a message's and of a whole iteration's bits, at the settings of the line items."""

    @F.udf("array<struct<method: string, message: double, iteration: double>>")
    def saved(d, n, t, p):
        made = [(m, compression(m, spec.parent, d, n, t, p)) for m, spec in METHODS.items() if spec.lattice]
        return [(m, round(c["message"], 9), round(c["iteration"], 9)) for m, c in made]

    rows = _items(spark, sf_dir, **LEDGER).withColumn("c", F.explode(saved("d", "n", "t", "p")))
    return rows.select("c.method", "d", "t", "p", "items", "c.message", "c.iteration")


QUERIES = {
    "w01_epoch_by_step": epoch_by_step,
    "w02_epoch_by_bits": epoch_by_items_bits,
    "w02_epoch_by_bits_figure": _epoch_by_bits(FIGURE_NOISE),
    "w09_bits_by_dimension": bits_by_dimension,
    "h01_h08_bounds": bounds,
    "h09_h13_targets": targets,
    "h11_h12_step_windows": step_windows,
    "m14_draws": uniforms,
    "m09_random_rounding": _rounding(True),
    "m10_nearest_rounding": _rounding(False),
    "m11_lattice_points": lattice_points,
    "m12_codec": codec_round_trip,
    "c14_w14_rounding_bias": unbiased,
    "c14_w14_bias_by_coordinate": bias_by_coordinate,
    "op_range_join_cells": cell_join,
    "c05_w13_ledger": ledger,
    "c07_w08_compression": compressed,
}
_P = "unnest(range({a}, {b}))::INTEGER AS p"
_T = "(VALUES (0.2::DOUBLE), (0.5), (0.9), (0.99)) x(target)"
_E = "(SELECT vec_id, CAST(i - 1 AS INTEGER) AS dim, embedding[i]::DOUBLE AS v FROM embeddings, range(1, 65) r(i))"
_NUM = f"{L}::DOUBLE", f"{MU}::DOUBLE", f"{DIM}::DOUBLE"


def _by_items_bits_sql() -> str:
    a = th.best_step_sql("target", *_NUM, "p")
    return f"SELECT target, p, items, CAST(ceil({th.epoch_sql('target', _NUM[0], _NUM[1], 'a', _NUM[2], 'p')}) AS BIGINT) AS t_min FROM (SELECT *, {a} AS a FROM ({_items_sql(**BY_BITS)}))"


def _by_bits_sql(noise: float) -> str:
    a = th.best_step_sql("target", _NUM[0], _NUM[1], _NUM[2], "p", noise)
    return f"WITH g AS (SELECT target, p, {a} AS a FROM {_T}, (SELECT {_P.format(a=8, b=33)})) SELECT target, p, CAST(ceil({th.epoch_sql('target', _NUM[0], _NUM[1], 'a', _NUM[2], 'p', noise)}) AS BIGINT) AS t_min FROM g"


def _ledger_sql(settings: str, more: str = "") -> str:
    anchored = "64 * d * n"
    cost = {
        "gd": "64 * d * (1 + n)", "sgd": "128 * d", "sag": "128 * d", "q_gd": "p * d + p * d * n", "q_sgd": "2 * p * d", "q_sag": "2 * p * d",
        "avr": f"{anchored} + 192 * d * t", "avr_memory": f"{anchored} + 192 * d * t", "qavr_model_only": f"{anchored} + 128 * d * t + p * d * t",
    }
    for m in ("qavr_fixed", "qavrm_fixed", "qavrm_adaptive", "qavr_adaptive"):
        cost[m] = f"{anchored} + 64 * d * t + 2 * p * d * t"
    for m in ("qavrm_fixed_plus", "qavrm_adaptive_plus", "qavr_adaptive_plus"):
        cost[m] = f"{anchored} + 2 * p * d * t"
    return " UNION ALL ".join(f"SELECT '{m}' AS method, d::BIGINT AS d, n::BIGINT AS n, t::BIGINT AS t, p::BIGINT AS p, {more} CAST({c} AS BIGINT) AS bits FROM {settings}" for m, c in cost.items())


def _compressed_sql() -> str:
    values = ", ".join(f"('{m}', '{spec.parent}')" for m, spec in METHODS.items() if spec.lattice)
    return f"""WITH i AS ({_items_sql(**LEDGER)}), b AS ({_ledger_sql('i', 'items,')})
SELECT o.method, o.d, o.t, o.p, o.items, round(1 - o.p / 64.0::DOUBLE, 9) AS message, round(1 - o.bits / w.bits::DOUBLE, 9) AS iteration
FROM b o JOIN (VALUES {values}) x(method, parent) ON o.method = x.method JOIN b w ON w.method = x.parent AND w.d = o.d AND w.n = o.n AND w.t = o.t AND w.p = o.p"""


def _bounds_sql() -> str:
    noise = "4 * l * d * (1 + 3 * l * l * a * a) / (mu * power(power(2.0, p) - 1, 2))"
    room = "(mu * a * (1 - 6 * l * a))"
    grid = f"({_items_sql(**_of('a', 'p'))}), (SELECT {_NUM[0]} AS l, {_NUM[1]} AS mu, {_NUM[2]} AS d, {LONG}::DOUBLE AS t)"
    return f"""SELECT a, p, items, round(CASE WHEN {room} > 0 THEN 1 / {room} END, 6) AS fixed_epoch, round((1 / (mu * t) + 3 * l * a * a) / (a - 3 * l * a * a), 6) AS fixed_rate,
CASE WHEN 1 - 6 * l * a > 0 THEN ceil(log2(1 + sqrt(4 * l * d * (1 + 3 * l * l * a * a) / (mu * mu * a * (1 - 6 * l * a))))) END AS bits,
round(CASE WHEN {room} - {noise} > 0 THEN 1 / ({room} - {noise}) END, 6) AS epoch, round((1 / t + 3 * mu * l * a * a + {noise}) / (mu * (a - 3 * l * a * a)), 6) AS rate FROM {grid}"""


def _windows_sql() -> str:
    h = "(4 * l * d / (mu * power(power(2.0, p) - 1, 2)))"
    bend = f"(3 * l * mu * (1 + target) + 3 * l * l * {h})"
    root = f"sqrt(mu * mu * target * target - 4 * {bend} * {h})"
    some = f"mu * mu * target * target > 4 * {bend} * {h}"
    grid = f"({_items_sql(**_of('target', 'p'))}), (SELECT {_NUM[0]} AS l, {_NUM[1]} AS mu, {_NUM[2]} AS d)"
    return f"""SELECT target, p, items, CASE WHEN {some} THEN round((mu * target - {root}) / (2 * {bend}), 9) END AS low, CASE WHEN {some} THEN round((mu * target + {root}) / (2 * {bend}), 9) END AS high,
round(mu * target / (2 * {bend}), 9) AS best FROM {grid}"""


def _targets_sql() -> str:
    a = th.best_step_sql("target", *_NUM, "15")
    room = "(target - 3 * l * a * target - 3 * l * a)"
    return f"""SELECT target, items, round(a, 9) AS a, CAST(ceil(log2(1 + sqrt(4 * l * d * (1 + 3 * l * l * a * a) / (mu * mu * a * {room})))) AS INTEGER) AS bits,
round(1 / (mu * a * {room} - 4 * l * d * (1 + 3 * l * l * a * a) / (mu * power(power(2.0, 15) - 1, 2))), 9) AS epoch, round(d * 4 / (mu * mu) / power(power(2.0, 15) - 1, 2), 9) AS variance_cap,
round(2 * l / mu, 9) AS grad_radius, round(1 / (6 * l), 9) AS step_limit,
round((3 * {LONG} * 0.01::DOUBLE * 0.0001::DOUBLE + 8 * 0.0001::DOUBLE) / (2 * {LONG} * 0.1::DOUBLE - 12 * l * {LONG} * 0.01::DOUBLE - 2 / mu), 9) AS ball
FROM (SELECT target, items, {a} AS a, {_NUM[0]} AS l, {_NUM[1]} AS mu, {_NUM[2]} AS d FROM ({_items_sql(**_of("target"))}))"""


_ROUND = round_sql("v", "0.0::DOUBLE", "0.25::DOUBLE", "4.0::DOUBLE", "{u}")
ORACLES = {
    "w01_epoch_by_step": f"SELECT target, p, a, items, round({th.epoch_sql('target', _NUM[0], _NUM[1], 'a', _NUM[2], 'p')}, 4) AS t_min FROM ({_items_sql(**_of('target', 'p', 'a'))})",
    "w02_epoch_by_bits": _by_items_bits_sql(),
    "w02_epoch_by_bits_figure": _by_bits_sql(FIGURE_NOISE),
    "w09_bits_by_dimension": f"SELECT d, CAST(ceil(log2(1 + sqrt(4 * {L}::DOUBLE * d * (1 + 3 * {L}::DOUBLE * {L}::DOUBLE * 0.0025::DOUBLE) / (0.04::DOUBLE * 0.05::DOUBLE * (1 - 6 * {L}::DOUBLE * 0.05::DOUBLE))))) AS INTEGER) AS p_min FROM (VALUES (10), (32), (100), (316), (1000)) v(d)",
    "m14_draws": f"SELECT k, u, CAST(floor(u * 10) AS INTEGER) AS worker, CAST(floor(v * 8) AS INTEGER) AS step FROM (SELECT k, {duck_uniform(chr(39) + '42|worker|' + chr(39) + ' || k || ' + chr(39) + '|1|0' + chr(39))} AS u, {duck_uniform(chr(39) + '42|pick|' + chr(39) + ' || k || ' + chr(39) + '|0|0' + chr(39))} AS v FROM (SELECT event_id AS k FROM events))",
    "m09_random_rounding": f"SELECT vec_id, dim, round({_ROUND.format(u=duck_uniform(chr(39) + '7|model|1|' + chr(39) + ' || vec_id || ' + chr(39) + '|' + chr(39) + ' || dim'))}, 9) AS q, abs(v) > 0.25 AS saturated FROM {_E}",
    "m10_nearest_rounding": f"SELECT vec_id, dim, round({_ROUND.format(u='0.5::DOUBLE')}, 9) AS q, abs(v) > 0.25 AS saturated FROM {_E}",
    "m11_lattice_points": f"SELECT target, p, items, CAST(j AS INTEGER) AS j, round(target - 1 + j * (2.0::DOUBLE / (power(2.0::DOUBLE, p) - 1)), 9) AS point FROM ({_items_sql(**LATTICES)}), range(0, 64) r(j) WHERE j < power(2, p)",
    "op_range_join_cells": f"SELECT dim, CAST(least(greatest(floor(v * 30 + 7.5), 0), 14) AS INTEGER) AS cell, count(*) AS n FROM {_E} GROUP BY ALL",
    "h01_h08_bounds": _bounds_sql(),
    "h09_h13_targets": _targets_sql(),
    "h11_h12_step_windows": _windows_sql(),
    "c07_w08_compression": _compressed_sql(),
    "c14_w14_rounding_bias": "SELECT round(v, 9) AS v, count(*) AS n, round(abs(avg(q) - any_value(v)), 9) AS abs_bias, round(max(abs(q - v)), 9) AS max_err, round(avg((q - v) * (q - v)), 9) AS mse FROM (SELECT v, "
    + round_sql("v", "0.0::DOUBLE", "1.0::DOUBLE", "3.0::DOUBLE", duck_uniform("s || '|model|1|1'"))
    + f" AS q FROM (SELECT {ITEM_KEY} AS s, (l_quantity::DOUBLE - 25.5::DOUBLE) / 24.5::DOUBLE AS v FROM lineitem)) GROUP BY round(v, 9)",
    "c14_w14_bias_by_coordinate": "SELECT dim, round(avg(e), 9) AS bias, round(max(abs(e)), 9) AS max_err, round(avg(e * e), 9) AS mse, count(e) AS n FROM (SELECT dim, "
    + _ROUND.format(u=duck_uniform("s || '|model|2|' || vec_id || '|' || dim"))
    + f" - v AS e FROM (SELECT vec_id, dim, greatest(least(v, 0.25::DOUBLE), -0.25::DOUBLE) AS v FROM {_E}), range(16) r(s)) GROUP BY dim",
    "m12_codec": "SELECT vec_id, 40::INTEGER AS bytes, true AS same, lpad(bin(least(greatest(floor((embedding[1] + 0.5) * 31), 0), 31)::BIGINT), 5, '0') || lpad(bin(least(greatest(floor((embedding[2] + 0.5) * 31), 0), 31)::BIGINT), 5, '0') AS head FROM embeddings",
    "c05_w13_ledger": f"WITH i AS ({_items_sql(**LEDGER)}) {_ledger_sql('i', 'items,')}",
}
