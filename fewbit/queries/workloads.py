"""The experiments: methods side by side on the tasks, their measures and ablations.

The queries w03 to w07 run the published 50 rounds; `compare` and `f1_table` take any number.
"""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import functions as F

from fewbit.functions import theory as th
from fewbit.operators import metrics, tasks
from fewbit.plans.config import Config
from fewbit.plans.driver import Run, fit_many, reference_optimum, with_bits
from fewbit.plans.methods import METHODS
from fewbit.functions.ledger import bits_paper
from fewbit.queries.methods import SEED, optimum_sql, train
from fewbit.queries.twin import CHARGE, D, N, method_sql

COMPARED = ("gd", "sgd", "sag", "avr", "avr_memory", "q_gd", "q_sgd", "q_sag", "qavrm_fixed", "qavrm_adaptive", "qavrm_fixed_plus", "qavrm_adaptive_plus")
SCALES = (1.0, 0.1)
ROUNDS = 50


def compare(spark, sf_dir, task: str, p: int, steps: int, rounds: int, cls: int = 1, methods=COMPARED, scales=SCALES, engine="measured"):
    """(method, radius_scale, k, loss, grad_norm, gap, f1, bits, rejected): every method at both radii, one batch of runs."""
    return _compared(spark, sf_dir, task, (p,), steps, rounds, cls, methods, scales, engine).drop("p")


def _compared(spark, sf_dir, task, bits, steps, rounds, cls=1, methods=COMPARED, scales=SCALES, engine="measured"):
    """compare at several numbers of bits, with p: the table is read once for all runs, their optimum and their scores."""
    d = tasks.TASKS[task][1]
    pts = tasks.samples(spark, sf_dir, task).persist()
    base = Config(rounds=rounds, steps=steps)
    # methods without a lattice don't depend on the radius
    runs = [Run(m, replace(with_bits(base, p), radius_scale=s), cls) for p in bits for m in methods for s in (scales if METHODS[m].lattice else scales[:1])]
    out = fit_many(pts.where("split = 'train'"), runs, d, engine, optimum=True)
    last = {s.run.name: {cls: s.kept.model} for s in out.states}
    f1 = metrics.f1(metrics.confusion(pts.where("split = 'test'"), last, d)).where("rule = 'sign'").select(F.col("name").alias("run_id"), F.col("f1"))
    scale = spark.createDataFrame([(r.name, r.config.radius_scale) for r in runs], "run_id string, radius_scale double")
    trace = metrics.gap(out.trace(spark), out.optimum[1])
    rejected = F.sum(F.when(F.col("accepted"), 0).otherwise(1)).over(metrics.Window.partitionBy("run_id").orderBy("k"))
    rows = trace.withColumn("rejected", rejected).join(F.broadcast(scale), "run_id").join(f1, "run_id").select(
        "method", "radius_scale", "k", "loss", "grad_norm", "gap", "f1", F.col("cum_bits_paper").alias("bits"), "rejected", "saturated", "status", "p"
    )
    rows = spark.createDataFrame(rows.collect(), rows.schema)
    pts.unpersist()
    return rows


def few_bits(spark, sf_dir):
    """Binary task at 3 bits a coordinate."""
    return compare(spark, sf_dir, "charge", 3, 8, ROUNDS)


def more_bits(spark, sf_dir):
    """Binary task at 9 bits."""
    return compare(spark, sf_dir, "charge", 9, 8, ROUNDS)


def _one_class(p):
    def query(spark, sf_dir):
        return compare(spark, sf_dir, "language", p, 15, ROUNDS, cls=3)

    return query


def _anchor_class(p):
    def query(spark, sf_dir):
        return compare(spark, sf_dir, "anchor10", p, 15, ROUNDS, cls=9)

    return query


TABLE = ("gd", "avr_memory", "q_gd", "q_sgd", "q_sag", "qavrm_fixed_plus", "qavrm_adaptive_plus")


def one_vs_all(spark, sf_dir, task: str, bits, rounds: int, scales=SCALES, methods=TABLE):
    """{run set: {class: model}} scored on the test samples: all classes, methods, bits and radii in one batch of runs."""
    _, d, classes = tasks.TASKS[task]
    pts = tasks.samples(spark, sf_dir, task).persist()
    base = Config(rounds=rounds, steps=15)
    runs = [
        Run(m, replace(with_bits(base, p), radius_scale=s), c)
        for p in bits for m in methods for s in (scales if METHODS[m].lattice else scales[:1]) for c in range(classes)
    ]
    out = fit_many(pts.where("split = 'train'"), runs, d, "measured")
    models: dict[str, dict[int, np.ndarray]] = {}
    for s in out.states:
        # a diverged run has no model that scores; its last finite one stands for it
        models.setdefault(f"{s.run.method}|{s.run.config.model_bits}|{s.run.config.radius_scale:g}", {})[s.run.cls] = s.kept.model
    counts = metrics.confusion(pts.where("split = 'test'"), models, d)
    return counts, pts


def f1_table(spark, sf_dir, task="language", rounds=ROUNDS, one=3, bits=(7, 10)):
    """(p, method, radius_scale, rule, f1_one, f1_macro): the comparison of test scores."""
    counts, pts = one_vs_all(spark, sf_dir, task, bits, rounds)
    counts = spark.createDataFrame(counts.collect(), counts.schema)
    pts.unpersist()
    both = metrics.f1(counts).where(F.col("cls") == one).select("name", "rule", F.col("f1").alias("f1_one")).join(metrics.f1_macro(counts), ["name", "rule"])
    split = F.split("name", r"\|")
    rows = both.select(split[1].cast("int").alias("p"), split[0].alias("method"), split[2].cast("double").alias("radius_scale"), "rule", "f1_one", "f1_macro").collect()
    return spark.createDataFrame(rows, "p int, method string, radius_scale double, rule string, f1_one double, f1_macro double")


def f1_anchor(spark, sf_dir):
    return f1_table(spark, sf_dir, "anchor10", one=9)


def f1_noise(spark, sf_dir):
    """The negative control: scores stay at chance."""
    return f1_table(spark, sf_dir, "noise10", one=9)


def f1_pivot(spark, sf_dir):
    """The table in the shape of one row per number of bits, one column per method, at both radii and by both rules."""
    t = f1_table(spark, sf_dir)
    plain = t.where(~F.col("method").startswith("q")).drop("radius_scale").crossJoin(spark.createDataFrame([(v,) for v in SCALES], "radius_scale double"))
    every = t.where(F.col("method").startswith("q")).unionByName(plain)
    return every.groupBy("p", "radius_scale", "rule").pivot("method", list(TABLE)).agg(F.round(F.first("f1_macro"), 4))


SWEEP = (1.0, 0.5, 0.25, 0.1, 0.05)


def radius_sweep(spark, sf_dir):
    """Binary task at 3 bits: the same five radii for the fixed lattices and for the adaptive one; last gap and rejected epochs."""
    methods = ("q_gd", "q_sgd", "q_sag", "qavrm_fixed_plus", "qavrm_adaptive_plus")
    t = compare(spark, sf_dir, "charge", 3, 8, ROUNDS, methods=methods, scales=SWEEP)
    last = F.max_by(F.struct("gap", "rejected", "status"), "k").alias("l")
    return t.groupBy("method", "radius_scale").agg(last).select("method", "radius_scale", "l.*")


def memory_effect(spark, sf_dir):
    """With and without the memory, at few and at more bits."""
    methods = ("avr", "avr_memory", "qavr_adaptive", "qavrm_adaptive", "qavr_adaptive_plus", "qavrm_adaptive_plus")
    return _compared(spark, sf_dir, "charge", (5, 9), 8, ROUNDS, methods=methods, scales=(1.0,))


def as_good_as_exact(spark, sf_dir):
    """15 bits and more beside no rounding."""
    pts = train(spark, sf_dir)
    runs = [Run("qavrm_adaptive_plus", Config(rounds=ROUNDS, model_bits=p, grad_bits=p)) for p in (15, 32, 52, 64)]
    out = fit_many(pts, runs, 9, "measured").trace(spark).select("p", "k", "loss", "grad_norm")
    pts.unpersist()
    return out


def practical_steps(spark, sf_dir):
    """The epoch length used beside the least one that the bounds ask for."""
    from fewbit.operators.objective import geometry

    g = geometry(tasks.charge(spark, sf_dir).where("split = 'train'"), 0.1)
    rows = [(target, 8, float(np.ceil(th.epoch_best(target, g.average, g.mu, 9, 15)))) for target in (0.2, 0.5, 0.9, 0.99)]
    return spark.createDataFrame(rows, "target double, used int, bound double")


def _practical_sql() -> str:
    a = th.best_step_sql("target", "smooth", "0.2::DOUBLE", "9.0::DOUBLE", "15")
    square = " + ".join(f"x{i} * x{i}" for i in range(D))
    geo = f"(SELECT avg(q) / 4 + 0.2 AS smooth FROM (SELECT avg({square}) AS q FROM charge WHERE split = 'train' GROUP BY worker_id))"
    best = f"(SELECT target, smooth, {a} AS a FROM {geo}, (VALUES (0.2::DOUBLE), (0.5), (0.9), (0.99)) t(target))"
    return f"WITH {CHARGE.strip()} SELECT target, 8::INTEGER AS used, ceil({th.epoch_sql('target', 'smooth', '0.2::DOUBLE', 'a', '9.0::DOUBLE', '15')}) AS bound FROM {best}"


def ablations(spark, sf_dir):
    """Choices that the methods leave open, on the binary task."""
    pts = train(spark, sf_dir)
    base = Config(rounds=ROUNDS, model_bits=7, grad_bits=7)
    named = {
        "base": base,
        "pick_last": replace(base, pick="last"),
        "pick_mean": replace(base, pick="mean"),
        "exact_anchor": replace(base, exact_anchor=True),
        "nearest": replace(base, rounding="nearest"),
        "worst_worker": replace(base, smoothness="worst_worker"),
        "by_sample": replace(base, weighting="sample"),
        "more_bits_on_first": replace(base, model_bits=tuple([9] * 4 + [5] * 5), grad_bits=tuple([9] * 4 + [5] * 5)),
        "falling_step": replace(base, step=tuple(0.2 * 0.95**k for k in range(ROUNDS))),
    }
    runs = [Run("qavrm_adaptive_plus", c, run_id=name) for name, c in named.items()]
    runs += [Run("qavr_model_only", base, run_id="model_only"), Run("sag", replace(base, sag_warm=True), run_id="sag_warm")]
    trace = fit_many(pts, runs, 9, "measured").trace(spark)
    pts.unpersist()
    _, best, _ = _optimum(spark, sf_dir)
    return metrics.contraction(metrics.gap(trace, best)).select("run_id", "k", "loss", "grad_norm", "gap", "contraction", "accepted")


def workers_effect(spark, sf_dir):
    """The same method with 2, 10 and 100 workers."""
    parts, numbers = [], (2, 10, 100)
    # read once: a worker of fewer has the samples of those workers of 100 that have its number as remainder
    pts = tasks.samples(spark, sf_dir, "charge", max(numbers)).where("split = 'train'").persist()
    for n in numbers:
        own = pts.withColumn("worker_id", F.pmod("worker_id", F.lit(n)).cast("int"))
        out = fit_many(own, [Run("qavrm_adaptive_plus", Config(workers=n, rounds=ROUNDS))], 9, "measured")
        parts += [(n, r[4], r[5], r[6], r[12]) for r in out.trace_rows()]
    pts.unpersist()
    return spark.createDataFrame(parts, "workers int, k int, loss double, grad_norm double, bits long")


def _optimum(spark, sf_dir):
    pts = train(spark, sf_dir)
    out = reference_optimum(pts, 9, engine="measured")
    pts.unpersist()
    return out


def _with_messages(spark, sf_dir, runs):
    pts = train(spark, sf_dir)
    out = fit_many(pts, runs, D, "measured", messages=True)
    pts.unpersist()
    return out


def message_measures(spark, sf_dir):
    """Rounding errors, saturation, bits and packed bytes by kind: measures on the messages of two runs."""
    base = Config(rounds=ROUNDS_SHORT, seed=SEED)
    m = _with_messages(spark, sf_dir, [Run("qavrm_adaptive_plus", base), Run("qavrm_fixed_plus", base)]).messages(spark)
    bits = m.groupBy("run_id", "k", "kind").agg(F.sum("bits").alias("bits"), F.sum(F.octet_length("payload")).alias("payload_bytes"), F.bool_and("travels").alias("travels"))
    return metrics.round_error(m).join(bits, ["run_id", "k", "kind"])


ROUNDS_SHORT = 5


def _messages_sql() -> str:
    """Bits, bytes and kinds of messages_sizes from the counts of messages alone."""
    parts = []
    for k in range(1, ROUNDS_SHORT + 2):
        parts.append(f"({k}, 'exact', {64 * D * N}, 0, true)")
        if k <= ROUNDS_SHORT:
            for kind, travels in (("grad", "true"), ("anchorgrad", "false"), ("model", "true")):
                parts.append(f"({k}, '{kind}', {8 * 9 * D}, {8 * -(-9 * D // 8)}, {travels})")
    runs = ", ".join(f"('{m}')" for m in ("qavrm_adaptive_plus", "qavrm_fixed_plus"))
    return f"SELECT method, CAST(k AS INTEGER) AS k, kind, CAST(bits AS BIGINT) AS bits, CAST(nullif(payload, 0) AS BIGINT) AS payload_bytes, travels FROM (VALUES {runs}) r(method), (VALUES {', '.join(parts)}) v(k, kind, bits, payload, travels)"


def message_sizes(spark, sf_dir):
    """The countable part of message_measures."""
    t = message_measures(spark, sf_dir)
    return t.select(F.split("run_id", "-")[0].alias("method"), "k", "kind", "bits", "payload_bytes", "travels")


def bits_cube(spark, sf_dir):
    """Bits that travelled, by method, direction and kind, with subtotals."""
    out = _with_messages(spark, sf_dir, [Run(m, Config(rounds=3, seed=SEED), run_id=m) for m in ("qavrm_adaptive_plus", "q_gd")])
    return metrics.bits_by_direction(out.messages(spark))


def _bits_cube_sql() -> str:
    rows = [("qavrm_adaptive_plus", "up", "exact", 64 * D, 4 * N), ("qavrm_adaptive_plus", "up", "grad", 9 * D, 24), ("qavrm_adaptive_plus", "down", "model", 9 * D, 24), ("q_gd", "up", "grad", 9 * D, 3 * N), ("q_gd", "down", "model", 9 * D, 3)]
    return f"SELECT run_id, direction, kind, CAST(sum(b * c) AS BIGINT) AS bits, CAST(sum(c) AS BIGINT) AS n FROM (VALUES {', '.join(map(str, rows))}) v(run_id, direction, kind, b, c) GROUP BY ROLLUP (run_id, direction, kind)"


def sql_views(spark, sf_dir):
    """The run's own views asked by SQL: bits that travelled beside the ledger's, and rows of the other views."""
    pts = train(spark, sf_dir)
    out = fit_many(pts, [Run("qavrm_adaptive_plus", Config(rounds=3, seed=SEED), run_id="one")], D, "measured", messages=True)
    out.views(spark, pts)
    made = spark.sql(
        "SELECT l.k, l.bits_wire, m.bits AS bits_sent, t.accepted, size(w.w) AS d, (SELECT count(*) FROM pts) AS rows FROM ledger l JOIN trace t USING (run_id, k) "
        "JOIN models w USING (run_id, k) JOIN (SELECT run_id, k, sum(bits) AS bits FROM messages WHERE travels GROUP BY run_id, k) m USING (run_id, k) WHERE l.run_id = :run",
        args={"run": "one"},
    )
    rows = spark.createDataFrame(made.collect(), made.schema)
    pts.unpersist()
    return rows


def _sql_views_sql() -> str:
    wire = f"{64 * D * N} + CASE WHEN k <= 3 THEN {2 * 8 * 9 * D} ELSE 0 END"
    return f"WITH {CHARGE.strip()} SELECT CAST(k AS INTEGER) AS k, CAST({wire} AS BIGINT) AS bits_wire, CAST({wire} AS BIGINT) AS bits_sent, true AS accepted, {D}::INTEGER AS d, (SELECT count(*) FROM charge WHERE split = 'train') AS rows FROM range(1, 5) r(k)"


CURVES = ("gd", "avr_memory", "qavrm_adaptive_plus")
LEVEL = 0.05


def _curves(spark, sf_dir):
    pts = train(spark, sf_dir)
    runs = [Run(m, Config(rounds=ROUNDS_SHORT, steps=4, seed=SEED), run_id=m) for m in CURVES]
    trace = fit_many(pts, runs, D, "measured").trace(spark).withColumn("loss", F.round("loss", 6))
    best = round(reference_optimum(pts, D, engine="measured")[1], 8)
    pts.unpersist()
    return metrics.contraction(metrics.gap(trace, best))


def curve_measures(spark, sf_dir):
    """Plateau of the gap, and rounds and bits to a level."""
    trace = _curves(spark, sf_dir)
    out = metrics.plateau(trace, 3).join(metrics.to_target(trace, "gap", LEVEL), "run_id")
    return out.select("run_id", F.round("gap_min", 6).alias("gap_min"), F.round("gap_mean", 6).alias("gap_mean"), "k", "bits")


def contraction_measures(spark, sf_dir):
    return _curves(spark, sf_dir).select("run_id", "k", F.round("gap", 6).alias("gap"), F.round("contraction", 4).alias("contraction"))


def _curves_sql() -> str:
    parts = []
    for m in CURVES:
        bits = bits_paper(m, D, N, 4, 9 * D, 9 * D)
        last = 0 if m == "gd" else 64 * D * N
        parts.append(f"SELECT '{m}' AS run_id, k, loss, least(k, {ROUNDS_SHORT}) * {bits} + CASE WHEN k > {ROUNDS_SHORT} THEN {last} ELSE 0 END AS cum FROM ({method_sql(m, ROUNDS_SHORT, 4, 0.2, 9, SEED)})")
    best = f"SELECT any_value(loss) AS best FROM ({optimum_sql()})"
    return f"WITH t AS ({' UNION ALL '.join(parts)}), o AS ({best}), g AS (SELECT run_id, k, loss - best AS gap, cum FROM t, o)\n"


def fixed_model_f1(spark, sf_dir):
    """F1 of given linear models on the held-out vectors, by class and averaged, by both rules."""
    pts = tasks.anchor10(spark, sf_dir).where("split = 'test'")
    at = lambda *on: np.bincount([i for i, _ in on], [v for _, v in on], 64)
    models = {"given": {c: at((c, 1.0), (c + 10, 1.0)) for c in range(10)}}
    counts = metrics.confusion(pts, models, 64)
    return metrics.f1(counts).join(metrics.f1_macro(counts), ["name", "rule"]).select("rule", "cls", "tp", "fp", "fn", F.round("f1", 6).alias("f1"), F.round("f1_macro", 6).alias("f1_macro"))


def _f1_sql() -> str:
    score = "list_transform(range(1, 11), lambda i: embedding[i]::DOUBLE + embedding[i + 10]::DOUBLE)"
    return f"""WITH s AS (SELECT list_position(embedding[1:10], list_max(embedding[1:10])) - 1 AS cls, {score} AS s FROM embeddings WHERE vec_id % 5 = 0),
r AS (SELECT s.cls AS own, c, s[c + 1] > 0 AS sign, list_position(s, list_max(s)) - 1 = c AS argmax FROM s, range(10) x(c)),
u AS (SELECT 'sign' AS rule, c, own = c AS "is", sign AS said FROM r UNION ALL SELECT 'argmax', c, own = c, argmax FROM r),
t AS (SELECT rule, CAST(c AS INTEGER) AS cls, count(*) FILTER (said AND "is") AS tp, count(*) FILTER (said AND NOT "is") AS fp, count(*) FILTER (NOT said AND "is") AS fn FROM u GROUP BY ALL),
f AS (SELECT *, CASE WHEN 2 * tp + fp + fn > 0 THEN 2 * tp / (2 * tp + fp + fn)::DOUBLE ELSE 0 END AS v FROM t)
SELECT rule, cls, tp, fp, fn, round(v, 6) AS f1, round(avg(v) OVER (PARTITION BY rule), 6) AS f1_macro FROM f"""


def unbalanced(spark, sf_dir):
    """The unbalanced binary task."""
    return compare(spark, sf_dir, "quality", 9, 8, ROUNDS, scales=(1.0,))


def sensor_task(spark, sf_dir):
    return compare(spark, sf_dir, "sensor", 9, 8, ROUNDS, scales=(1.0,))


QUERIES = {
    "w03_binary_3_bits": few_bits,
    "w04_binary_9_bits": more_bits,
    "w05_one_class_7_bits": _one_class(7),
    "w05_anchor_class_7_bits": _anchor_class(7),
    "w06_one_class_10_bits": _one_class(10),
    "w06_anchor_class_10_bits": _anchor_class(10),
    "w07_m18_f1_table": f1_table,
    "w07_f1_anchor10": f1_anchor,
    "w07_f1_noise10_control": f1_noise,
    "w07_f1_pivot": f1_pivot,
    "w10_fifteen_bits": as_good_as_exact,
    "w11_memory": memory_effect,
    "w12_practical_steps": practical_steps,
    "w15_ablations": ablations,
    "w15_workers": workers_effect,
    "w15_quality_task": unbalanced,
    "w15_sensor_task": sensor_task,
    "w03_radius_sweep": radius_sweep,
    "c03_c04_f1_of_given_models": fixed_model_f1,
    "c06_c09_c12_messages": message_measures,
    "c06_message_sizes": message_sizes,
    "c10_contraction": contraction_measures,
    "op_sql_views": sql_views,
    "c06_bits_rollup": bits_cube,
    "c08_c11_c13_curves": curve_measures,
}
ORACLES = {
    "w12_practical_steps": _practical_sql(),
    "c03_c04_f1_of_given_models": _f1_sql(),
    "c06_message_sizes": _messages_sql(),
    "c06_bits_rollup": _bits_cube_sql(),
    "op_sql_views": _sql_views_sql(),
    "c08_c11_c13_curves": _curves_sql()
    + f"""SELECT run_id, round(min(gap) FILTER (back <= 3), 6) AS gap_min, round(avg(gap) FILTER (back <= 3), 6) AS gap_mean, CAST(min(k) FILTER (gap <= {LEVEL}) AS INTEGER) AS k, CAST(min(cum) FILTER (gap <= {LEVEL}) AS BIGINT) AS bits
FROM (SELECT *, row_number() OVER (PARTITION BY run_id ORDER BY k DESC) AS back FROM g) GROUP BY run_id""",
    "c10_contraction": _curves_sql() + "SELECT run_id, CAST(k AS INTEGER) AS k, round(gap, 6) AS gap, round(gap / lag(gap) OVER (PARTITION BY run_id ORDER BY k), 4) AS contraction FROM g",
}
