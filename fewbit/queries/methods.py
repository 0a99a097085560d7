"""One query per method and baseline (a short run on the charge task, beside the same run in SQL), and the tasks."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from fewbit.functions import rng
from fewbit.operators import objective, tasks
from fewbit.plans.config import Config
from fewbit.plans.driver import Run, fit_many, reference_optimum
from fewbit.plans.methods import METHODS
from fewbit.functions.ledger import bits_paper
from fewbit.queries.twin import CHARGE, D, LAM, N, method_sql, settings_sql
from fewbit.sources import sharded

#: A seed whose picks all leave the anchor (3, 2, 1, 2, 1 of 4 steps).
ROUNDS, STEPS, SEED = 5, 4, 3
#: Bits and step: as published, so few bits that epochs are rejected, a step so long that the memory acts without rounding too.
SETTINGS = {"nine_bits": (9, 0.2), "four_bits": (4, 0.2), "long_step": (9, 8.0)}
FLAGSHIP = Config(rounds=10, seed=SEED)
NAMES = {
    "avr": "m01_avr", "avr_memory": "m02_avr_memory", "qavr_fixed": "m03_quantized_fixed", "qavrm_fixed": "m04_quantized_memory_fixed",
    "qavrm_adaptive": "m05_quantized_memory_adaptive", "qavrm_fixed_plus": "m06_fixed_plus", "qavrm_adaptive_plus": "m07_adaptive_plus",
    "qavr_adaptive": "m08_adaptive_without_memory", "qavr_adaptive_plus": "m08_adaptive_plus_without_memory", "gd": "b01_gd", "sgd": "b02_sgd",
    "sag": "b03_sag", "q_gd": "b04_quantized_gd", "q_sgd": "b05_quantized_sgd", "q_sag": "b06_quantized_sag", "qavr_model_only": "b09_model_only",
}


def train(spark, sf_dir, task="charge"):
    """Training samples of a task, kept for the passes of a run."""
    return tasks.TASKS[task][0](spark, sf_dir).where("split = 'train'").drop("split", "row_id").persist()


def method_runs(method: str, objective: str = "logistic") -> list[Run]:
    base = Config(rounds=ROUNDS, steps=STEPS, seed=SEED, objective=objective)
    return [Run(method, replace(base, model_bits=p, grad_bits=p, step=step), run_id=name) for name, (p, step) in SETTINGS.items()]


def run(method: str, engine: str = "measured", objective: str = "logistic"):
    def query(spark, sf_dir):
        pts = train(spark, sf_dir)
        out = fit_many(pts, method_runs(method, objective), D, engine).trace(spark)
        pts.unpersist()
        return out.select(F.col("run_id").alias("setting"), "k", F.round("loss", 6).alias("loss"), F.round("grad_norm", 6).alias("grad_norm"), "accepted")

    return query


def run_on_store(method: str):
    """The same on the sharded store: an inner step reads its worker's folder only."""

    def query(spark, sf_dir):
        pts = tasks.charge(spark, sf_dir).where("split = 'train'").drop("split")
        with sharded(pts) as shards:
            out = fit_many(shards, method_runs(method), D, "rounds").trace(spark)
        return out.select(F.col("run_id").alias("setting"), "k", F.round("loss", 6).alias("loss"), F.round("grad_norm", 6).alias("grad_norm"), "accepted")

    return query


def flagship(spark, sf_dir):
    """The adaptive lattice that rounds both gradients, with memory, on the sharded store: trace of ten rounds.

    The engine is named in the result: samples that one task may hold are held there, others are read shard by shard.
    """
    pts = tasks.charge(spark, sf_dir).where("split = 'train'").drop("split")
    with sharded(pts) as shards:
        out = fit_many(shards, [Run("qavrm_adaptive_plus", FLAGSHIP)], D, "measured")
    t = out.trace(spark).withColumn("engine", F.lit(out.engine))
    return t.select("method", "engine", "p", "k", F.round("loss", 6).alias("loss"), F.round("grad_norm", 6).alias("grad_norm"), "accepted", "closing", "bits_paper", "cum_bits_paper")


def _flagship_sql() -> str:
    c = FLAGSHIP
    bits = bits_paper("qavrm_adaptive_plus", D, N, c.steps, 9 * D, 9 * D)
    return f"""SELECT 'qavrm_adaptive_plus' AS method, 'held' AS engine, 9::INTEGER AS p, k, loss, grad_norm, accepted, k > {c.rounds} AS closing,
CASE WHEN k > {c.rounds} THEN {64 * D * N} ELSE {bits} END::BIGINT AS bits_paper, (least(k, {c.rounds}) * {bits} + CASE WHEN k > {c.rounds} THEN {64 * D * N} ELSE 0 END)::BIGINT AS cum_bits_paper
FROM ({method_sql("qavrm_adaptive_plus", c.rounds, c.steps, c.step, 9, SEED)})"""


def pass_costs(spark, sf_dir):
    """By epoch: whether its time was taken, rows scanned, and bytes of partial sums moved, of a run on the sharded store."""
    pts = tasks.charge(spark, sf_dir).where("split = 'train'").drop("split")
    with sharded(pts) as shards:
        out = fit_many(shards, [Run("avr_memory", Config(rounds=ROUNDS, steps=STEPS, seed=SEED))], D, "rounds").cost(spark)
    return out.select("k", (F.col("seconds") > 0).alias("timed"), "rows_scanned", "bytes_moved")


def _costs_sql() -> str:
    drawn = ", ".join(f"({k}, {rng.worker(SEED, k, t, N)})" for k in range(1, ROUNDS + 1) for t in range(1, STEPS + 1))
    return f"""WITH {CHARGE.strip()}, own AS (SELECT worker_id, count(*) AS n FROM charge WHERE split = 'train' GROUP BY 1),
drawn(k, worker_id) AS (VALUES {drawn}), inner_rows AS (SELECT k, sum(n) AS n FROM drawn JOIN own USING (worker_id) GROUP BY k)
SELECT CAST(k AS INTEGER) AS k, true AS timed, CAST((SELECT sum(n) FROM own) + coalesce(n, 0) AS BIGINT) AS rows_scanned,
CAST(8 * {D} * ({N} + CASE WHEN k <= {ROUNDS} THEN {STEPS} ELSE 0 END) AS BIGINT) AS bytes_moved FROM range(1, {ROUNDS + 2}) r(k) LEFT JOIN inner_rows USING (k)"""


def least_squares_moments(spark, sf_dir):
    """What the closed form of the ridge least squares is solved from."""
    m = objective.moments(_pts(spark, sf_dir), D)
    return m.select("i", "j", F.round("m", 8).alias("m"))


def least_squares_optimum(spark, sf_dir):
    """The closed form beside the rounded method after 40 rounds; the gradient of the closed form is zero."""
    pts = train(spark, sf_dir)
    exact = objective.least_squares_optimum(pts, D, LAM)
    config = Config(rounds=40, seed=SEED, step=0.1, objective="squares")
    out = fit_many(pts, [Run("qavrm_adaptive_plus", config), Run("gd", replace(config, start=tuple(exact), rounds=40))], D, "measured")
    pts.unpersist()
    found, at = out.states
    rows = [(i, float(w), float(v), float(at.trace[0][6])) for i, (w, v) in enumerate(zip(exact, found.kept.model, strict=True))]
    t = spark.createDataFrame(rows, "dim int, exact double, found double, norm double")
    return t.select("dim", F.round("exact", 6).alias("exact"), (F.abs(F.col("found") - F.col("exact")) < 0.05).alias("near"), (F.col("norm") < 1e-9).alias("stationary"))


def _models(spark, d=D):
    rows = [("zero", [0.0] * d), ("one", [0.1 * (i + 1) for i in range(d)])]
    return spark.createDataFrame(rows, "run_id string, w array<double>")


def gradient_wide(spark, sf_dir):
    wide = tasks.charge_wide(spark, sf_dir).where("split = 'train'")
    g = objective.gradients_wide(wide, _models(spark), D, LAM)
    return g.select("run_id", "worker_id", "n", F.round("loss", 8).alias("loss"), *[F.round(F.col("g")[i], 8).alias(f"g{i}") for i in range(D)])


def _pts(spark, sf_dir):
    return tasks.charge(spark, sf_dir).where("split = 'train'")


def gradient_long(spark, sf_dir):
    g = objective.gradients_long(_pts(spark, sf_dir), _models(spark), LAM)
    return g.groupBy("run_id", "worker_id").pivot("dim", list(range(D))).agg(F.first("g")).select("run_id", "worker_id", *[F.round(F.col(str(i)), 8).alias(f"g{i}") for i in range(D)])


def gradient_arrow(spark, sf_dir):
    import numpy as np

    models = [("zero", np.zeros(D)), ("one", 0.1 * np.arange(1, D + 1))]
    sums = objective.worker_sums(_pts(spark, sf_dir), np.array([w for _, w in models]), np.array([1, 1]))
    rows = []
    for worker, (n, g, s) in sums.items():
        for i, (name, w) in enumerate(models):
            own = g[i] / n + 2 * LAM * w
            rows.append((name, int(worker), int(n), float(round(s[i] / n + LAM * float(w @ w), 8)), *[float(round(v, 8)) for v in own]))
    return spark.createDataFrame(rows, "run_id string, worker_id int, n long, loss double, " + ", ".join(f"g{i} double" for i in range(D)))


def gradient_summarizer(spark, sf_dir):
    import numpy as np

    w = 0.1 * np.arange(1, D + 1)
    out = objective.gradients_summarizer(_pts(spark, sf_dir), w, LAM)
    rows = [("one", int(k), *[float(round(x, 8)) for x in v]) for k, v in out.items()]
    return spark.createDataFrame(rows, "run_id string, worker_id int, " + ", ".join(f"g{i} double" for i in range(D)))


def _gradient_sql(columns: str, where: str = "") -> str:
    dot = " + ".join(f"x{i} * w[{i + 1}]" for i in range(D))
    square = " + ".join(f"w[{i + 1}] * w[{i + 1}]" for i in range(D))
    g = ", ".join(f"round(avg(-y / (1 + exp(m)) * x{i}) + {2 * LAM} * any_value(w[{i + 1}]), 8) AS g{i}" for i in range(D))
    one = "[" + ", ".join(f"{0.1 * (i + 1)!r}::DOUBLE" for i in range(D)) + "]"
    return f"""WITH {CHARGE.strip()},
models(run_id, w) AS (VALUES ('zero', [{", ".join(["0.0::DOUBLE"] * D)}]), ('one', {one})),
rows AS (SELECT run_id, worker_id, w, y, y * ({dot}) AS m, {square} AS sq, {", ".join(f"x{i}" for i in range(D))}
    FROM (SELECT *, CASE WHEN cls = 1 THEN 1.0 ELSE -1.0 END::DOUBLE AS y FROM charge WHERE split = 'train'), models {where})
SELECT run_id, worker_id, {columns}{g} FROM rows GROUP BY run_id, worker_id"""


def geometry(spark, sf_dir):
    g = objective.geometry(_pts(spark, sf_dir), LAM)
    return spark.createDataFrame([(round(g.average, 8), round(g.worst, 8), round(g.mu, 8))], "average double, worst double, mu double")


def task_charge(spark, sf_dir):
    t = tasks.charge_wide(spark, sf_dir)
    return t.groupBy("worker_id", "split", "cls").agg(F.count("*").alias("n"), F.countDistinct("row_id").alias("ids"), *[(F.round(F.sum(f"x{i}"), 5) + 0.0).alias(f"s{i}") for i in range(D)])


def task_language(spark, sf_dir):
    c = tasks.language_cells(spark, sf_dir)
    return c.groupBy("bucket").agg(F.count("*").alias("cells"), F.sum("n").alias("grams"))


def task_language_rows(spark, sf_dir):
    """Rows by split, class and worker, with sums over their sparse features that tell indexes and values apart."""
    t = tasks.language(spark, sf_dir)
    return t.groupBy("split", "cls", "worker_id").agg(
        F.count("*").alias("n"), F.round(F.sum(F.expr("aggregate(val, 0D, (s, v) -> s + v)")), 5).alias("total"),
        F.round(F.sum(F.expr("aggregate(zip_with(idx, val, (i, v) -> i * v), 0D, (s, v) -> s + v)")) / 784, 5).alias("weighted"),
    )


def task_anchor10(spark, sf_dir):
    return tasks.anchor10(spark, sf_dir).groupBy("split", "cls").agg(F.count("*").alias("n"), F.round(F.sum(F.col("x")[0]), 6).alias("s0"))


def task_noise10(spark, sf_dir):
    return tasks.noise10(spark, sf_dir).groupBy("split", "cls").agg(F.count("*").alias("n"))


def task_quality(spark, sf_dir):
    return tasks.quality(spark, sf_dir).groupBy("cls").agg(F.count("*").alias("n"), *[F.round(F.sum(F.col("x")[i]), 5).alias(f"s{i}") for i in range(D)])


def task_sensor(spark, sf_dir):
    return tasks.sensor(spark, sf_dir).groupBy("worker_id", "split", "cls").agg(F.count("*").alias("n"), *[(F.round(F.sum(F.col("x")[i]), 5) + 0.0).alias(f"s{i}") for i in range(D)])


def threshold_label(spark, sf_dir):
    from fewbit.sources import load

    return load(spark, sf_dir, "events").select("event_id", tasks.threshold_label(F.col("value"), 35.0).alias("cls"))


def optimum(spark, sf_dir):
    """The exact optimum of the charge task, the reference for gaps: a model without gradient, measured by a scan of its own."""
    pts = train(spark, sf_dir)
    w, loss, norm = reference_optimum(pts, D, LAM, engine="measured")
    pts.unpersist()
    rows = [(i, float(v), loss, norm < 1e-9) for i, v in enumerate(w)]
    return spark.createDataFrame(rows, "dim int, w double, loss double, stationary boolean").select("dim", F.round("w", 6).alias("w"), F.round("loss", 8).alias("loss"), "stationary")


def optimum_sql(steps: int = 60) -> str:
    """Plain descent with momentum as one recursive statement, long enough for six digits."""
    dot = " + ".join(f"x{i} * v[{i + 1}]" for i in range(D))
    square = " + ".join(f"v[{i + 1}] * v[{i + 1}]" for i in range(D))
    grad = "[" + ", ".join(f"avg(g[{i + 1}])" for i in range(D)) + "]"
    own = "[" + ", ".join(f"avg(-y / (1 + exp(m)) * x{i}) + {2 * LAM} * any_value(v[{i + 1}])" for i in range(D)) + "]"
    after = "[" + ", ".join(f"v[{i + 1}] - g[{i + 1}] / smooth" for i in range(D)) + "]"
    moved = "[" + ", ".join(f"u[{i + 1}] + beta * (u[{i + 1}] - w[{i + 1}])" for i in range(D)) + "]"
    sq = " + ".join(f"x{i} * x{i}" for i in range(D))
    rows = f"SELECT p.worker_id, v, p.y, y * ({dot}) AS m, {square} AS sq, {', '.join(f'x{i}' for i in range(D))} FROM pts p, "
    out = [
        CHARGE.strip(), "pts AS MATERIALIZED (SELECT worker_id, CASE WHEN cls = 1 THEN 1.0 ELSE -1.0 END::DOUBLE AS y, " + ", ".join(f"x{i}" for i in range(D)) + " FROM charge WHERE split = 'train')",
        f"geo AS MATERIALIZED (SELECT smooth, (sqrt(smooth) - sqrt({2 * LAM})) / (sqrt(smooth) + sqrt({2 * LAM})) AS beta FROM (SELECT avg(q) / 4 + {2 * LAM} AS smooth FROM (SELECT avg({sq}) AS q FROM pts GROUP BY worker_id)))",
        "z0 AS (SELECT " + f"[{', '.join(['0.0::DOUBLE'] * D)}] AS w, [{', '.join(['0.0::DOUBLE'] * D)}] AS v)",
    ]
    for k in range(steps):
        out.append(f"e{k} AS (SELECT {grad} AS g FROM (SELECT {own} AS g FROM ({rows} z{k}) GROUP BY worker_id))")
        out.append(f"z{k + 1} AS MATERIALIZED (SELECT u AS w, {moved} AS v FROM (SELECT {after} AS u, w, beta FROM z{k}, e{k}, geo))")
    out.append(f"f AS (SELECT avg(l) AS l FROM (SELECT avg(greatest(-m, 0) + ln(1 + exp(-abs(m)))) + {LAM} * any_value(sq) AS l FROM ({rows} z{steps}) GROUP BY worker_id))")
    return "WITH " + ",\n".join(out) + f"\nSELECT CAST(i AS INTEGER) AS dim, round(v[i + 1], 6) AS w, round(l, 8) AS loss, true AS stationary FROM z{steps}, f, range({D}) r(i)"


def _quality_sql() -> str:
    share = lambda p: f"(length(text) - length(regexp_replace(text, '{p}', '', 'g'))) / n"
    x = [
        "ln(n) / 10", "ln(words) / 10", "n / words / 10", share("[0-9]"), share(r"[^\p{L}\s0-9]"), share(r"\p{Lu}"), "1 - len(list_distinct(lines)) / len(lines)::DOUBLE",
        "CASE WHEN lang = 'en' THEN 1.0 ELSE 0.0 END", "1.0",
    ]
    sums = ", ".join(f"round(sum(CAST({v} AS DOUBLE)), 5) AS s{i}" for i, v in enumerate(x))
    rows = r"SELECT *, greatest(length(text), 1)::DOUBLE AS n, len(regexp_split_to_array(text, '\s+'))::DOUBLE AS words, string_split(text, chr(10)) AS lines FROM documents JOIN labels USING (doc_id) WHERE quality IS NOT NULL"
    return f"SELECT quality AS cls, count(*) AS n, {sums} FROM ({rows}) GROUP BY quality"


def sensor_features_sql() -> list[str]:
    turn = "(hour(ts) + minute(ts) / 60.0::DOUBLE) * 0.2617993877991494"
    x = [f"sin({turn})", f"cos({turn})", "(dayofweek(ts) - 3) / 3.0::DOUBLE", "CASE WHEN dayofweek(ts) IN (0, 6) THEN 1 ELSE 0 END"]
    return x + [f"CASE WHEN event_type = '{kind}' THEN 1 ELSE 0 END" for kind in tasks.EVENT_TYPES] + ["1"]


def _sensor_sql() -> str:
    sums = ", ".join(f"round(sum(CAST({v} AS DOUBLE)), 5) + 0.0::DOUBLE AS s{i}" for i, v in enumerate(sensor_features_sql()))
    return f"SELECT CAST(user_id % 10 AS INTEGER) AS worker_id, CASE WHEN event_id % 5 = 0 THEN 'test' ELSE 'train' END AS split, CAST(CASE WHEN value > 35 THEN 1 ELSE 0 END AS INTEGER) AS cls, count(*) AS n, {sums} FROM events GROUP BY ALL"


QUERIES = {"flagship_adaptive_plus": flagship} | {NAMES[m]: run(m) for m in METHODS}
QUERIES |= {
    "m07_adaptive_plus_rounds_engine": run("qavrm_adaptive_plus", "rounds"),
    "m07_adaptive_plus_sharded_store": run_on_store("qavrm_adaptive_plus"),
    "m20_least_squares": run("qavrm_adaptive_plus", objective="squares"),
    "m20_least_squares_moments": least_squares_moments,
    "m20_least_squares_optimum": least_squares_optimum,
    "c15_pass_costs": pass_costs,
    "m15_m16_gradient_wide": gradient_wide,
    "m16_gradient_long": gradient_long,
    "m16_gradient_arrow": gradient_arrow,
    "m16_gradient_summarizer": gradient_summarizer,
    "m17_geometry": geometry,
    "m19_threshold_label": threshold_label,
    "b08_reference_optimum": optimum,
    "task_charge": task_charge,
    "task_language_cells": task_language,
    "task_language": task_language_rows,
    "task_anchor10": task_anchor10,
    "task_noise10": task_noise10,
    "task_quality": task_quality,
    "task_sensor": task_sensor,
}
ORACLES = {NAMES[m]: settings_sql(m, ROUNDS, STEPS, SEED, SETTINGS) for m in METHODS}
_SQUARE = " + ".join(f"x{i} * x{i}" for i in range(D))
_DOCS = "SELECT min_by(doc_id, doc_id) AS doc_id, min_by(lang, doc_id) AS lang, text FROM documents WHERE length(text) >= 3 GROUP BY text"
ORACLES |= {
    "flagship_adaptive_plus": _flagship_sql(),
    "m07_adaptive_plus_rounds_engine": settings_sql("qavrm_adaptive_plus", ROUNDS, STEPS, SEED, SETTINGS),
    "m07_adaptive_plus_sharded_store": settings_sql("qavrm_adaptive_plus", ROUNDS, STEPS, SEED, SETTINGS),
    "m20_least_squares": settings_sql("qavrm_adaptive_plus", ROUNDS, STEPS, SEED, SETTINGS, "squares"),
    "m20_least_squares_moments": f"WITH {CHARGE.strip()} " + " UNION ALL ".join(
        f"SELECT {i}::INTEGER AS i, {j}::INTEGER AS j, round(avg(m), 8) AS m FROM (SELECT avg(x{i} * {f'x{j}' if j < D else 'CASE WHEN cls = 1 THEN 1.0 ELSE -1.0 END'}) AS m FROM charge WHERE split = 'train' GROUP BY worker_id)"
        for i in range(D) for j in range(i, D + 1)
    ),
    "c15_pass_costs": _costs_sql(),
    "b08_reference_optimum": optimum_sql(),
    "m15_m16_gradient_wide": _gradient_sql(f"count(*) AS n, round(avg(greatest(-m, 0) + ln(1 + exp(-abs(m)))) + {LAM} * any_value(sq), 8) AS loss, "),
    "m16_gradient_arrow": _gradient_sql(f"count(*) AS n, round(avg(greatest(-m, 0) + ln(1 + exp(-abs(m)))) + {LAM} * any_value(sq), 8) AS loss, "),
    "m16_gradient_long": _gradient_sql(""),
    "m16_gradient_summarizer": _gradient_sql("", "WHERE run_id = 'one'"),
    "m17_geometry": f"WITH {CHARGE.strip()} SELECT round(avg(q) / 4 + 0.2, 8) AS average, round(max(q) / 4 + 0.2, 8) AS worst, 0.2::DOUBLE AS mu FROM (SELECT avg({_SQUARE}) AS q FROM charge WHERE split = 'train' GROUP BY worker_id)",
    "m19_threshold_label": "SELECT event_id, CAST(CASE WHEN value > 35 THEN 1 ELSE 0 END AS INTEGER) AS cls FROM events",
    "task_charge": f"WITH {CHARGE.strip()} SELECT worker_id, split, CAST(cls AS INTEGER) AS cls, count(*) AS n, count(DISTINCT row_id) AS ids, "
    + ", ".join(f"round(sum(x{i}), 5) + 0.0::DOUBLE AS s{i}" for i in range(D))
    + " FROM charge GROUP BY ALL",
    "task_language_cells": f"""WITH own AS ({_DOCS}),
g AS (SELECT doc_id, unnest(list_transform(range(1, length(s) - 1), lambda i: substring(s, i, 3))) AS g FROM (SELECT doc_id, substring(text, pos, 1002) AS s FROM (SELECT doc_id, text, unnest(range(1, length(text) - 1, 1000)) AS pos FROM own))),
c AS (SELECT doc_id, CAST(('0x' || substr(md5(g), 1, 8))::BIGINT % 784 AS INTEGER) AS bucket, count(*) AS n FROM g GROUP BY ALL)
SELECT bucket, count(*) AS cells, CAST(sum(n) AS BIGINT) AS grams FROM c GROUP BY bucket""",
    "task_language": f"""WITH own AS ({_DOCS}),
g AS (SELECT doc_id, unnest(list_transform(range(1, length(s) - 1), lambda i: substring(s, i, 3))) AS g FROM (SELECT doc_id, substring(text, pos, 1002) AS s FROM (SELECT doc_id, text, unnest(range(1, length(text) - 1, 1000)) AS pos FROM own))),
c AS (SELECT doc_id, CAST(('0x' || substr(md5(g), 1, 8))::BIGINT % 784 AS INTEGER) AS bucket, count(*)::DOUBLE AS n FROM g GROUP BY ALL),
v AS (SELECT doc_id, sum(n) / sqrt(sum(n * n)) * 3 AS total, sum(bucket * n) / sqrt(sum(n * n)) * 3 / 784 AS weighted FROM c GROUP BY doc_id)
SELECT CASE WHEN ('0x' || substr(md5(text), 1, 8))::BIGINT % 5 = 0 THEN 'test' ELSE 'train' END AS split,
CAST(list_position(['en', 'fr', 'de', 'es'], lang) - 1 AS INTEGER) AS cls, CAST(doc_id % 10 AS INTEGER) AS worker_id, count(*) AS n, round(sum(total), 5) AS total, round(sum(weighted), 5) AS weighted
FROM own JOIN v USING (doc_id) GROUP BY ALL""",
    "task_anchor10": "SELECT CASE WHEN vec_id % 5 = 0 THEN 'test' ELSE 'train' END AS split, CAST(list_position(embedding[1:10], list_max(embedding[1:10])) - 1 AS INTEGER) AS cls, count(*) AS n, round(sum(embedding[1]::DOUBLE), 6) AS s0 FROM embeddings GROUP BY ALL",
    "task_noise10": "SELECT CASE WHEN vec_id % 5 = 0 THEN 'test' ELSE 'train' END AS split, label AS cls, count(*) AS n FROM embeddings GROUP BY ALL",
    "task_quality": _quality_sql(),
    "task_sensor": _sensor_sql(),
}
