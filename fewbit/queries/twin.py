"""SQL that runs a few rounds of any method step by step, as an independent check of the driver.

Each step is a common table expression of one row (or one per worker) with vectors as lists; the draws are taken from the
same md5 keys. Written for DuckDB.
"""

from __future__ import annotations

from fewbit.functions.lattice import round_sql
from fewbit.functions.rng import duck_uniform
from fewbit.plans.methods import METHODS

ROW_KEY = "concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_shipdate)"
CHARGE = f"""
charge AS (SELECT md5({ROW_KEY}) AS row_id, CAST(l_orderkey % 10 AS INTEGER) AS worker_id,
    CASE WHEN ('0x' || substr(md5({ROW_KEY}), 1, 8))::BIGINT % 5 = 0 THEN 'test' ELSE 'train' END AS split,
    CASE WHEN l_extendedprice * (1 - l_discount) * (1 + l_tax) > 50000 THEN 1 ELSE 0 END AS cls,
    (l_quantity - 25.5) / 24.5 AS x0, (l_extendedprice - 53000) / 52500 AS x1, (l_discount - 0.05) / 0.05 AS x2,
    (l_tax - 0.04) / 0.04 AS x3, CAST(l_linenumber - 4 AS DOUBLE) / 3 AS x4, (p_size - 25.5::DOUBLE) / 24.5::DOUBLE AS x5,
    (month(l_shipdate) - 6.5::DOUBLE) / 5.5::DOUBLE AS x6, CAST(dayofweek(l_shipdate) - 3 AS DOUBLE) / 3 AS x7, 1.0::DOUBLE AS x8
    FROM lineitem JOIN part ON l_partkey = p_partkey)"""
D, LAM, N = 9, 0.1, 10


def _list(made) -> str:
    return "[" + ", ".join(made) + "]"


def _gradients(name: str, model: str, where: str = "", objective: str = "logistic") -> str:
    """name(worker_id, l, g) at the model of a one-row table."""
    pull, loss = {
        "logistic": ("-y / (1 + exp(m))", "greatest(-m, 0) + ln(1 + exp(-abs(m)))"),
        "squares": ("y * (m - 1)", "(m - 1) * (m - 1) / 2"),
    }[objective]
    dot = " + ".join(f"x{i} * w[{i + 1}]" for i in range(D))
    square = " + ".join(f"w[{i + 1}] * w[{i + 1}]" for i in range(D))
    g = _list(f"avg({pull} * x{i}) + {2 * LAM} * any_value(w[{i + 1}])" for i in range(D))
    return (
        f"{name} AS (SELECT worker_id, avg({loss}) + {LAM} * any_value(sq) AS l, {g} AS g "
        f"FROM (SELECT p.*, w, y * ({dot}) AS m, {square} AS sq FROM pts p, {model} {where}) GROUP BY worker_id)"
    )


def _round(v: str, center: str, radius: str, p: int, stream: str, k: int, t: int, seed: int) -> str:
    """List expression: v rounded around center; stream may be an SQL string expression."""
    return _list(
        round_sql(f"{v}[{i + 1}]", f"{center}[{i + 1}]", radius, f"{p}::DOUBLE", duck_uniform(f"'{seed}|' || {stream} || '|{k}|{t}|{i}'"))
        for i in range(D)
    )


def method_sql(method: str, rounds: int, steps: int, step: float, p: int, seed: int = 42, scale: float = 1.0, objective: str = "logistic") -> str:
    """SQL for (k, loss, grad_norm, accepted) of a run on `charge`, its closing pass included."""
    spec = METHODS[method]
    out = [CHARGE.strip(), "pts AS MATERIALIZED (SELECT worker_id, CASE WHEN cls = 1 THEN 1.0 ELSE -1.0 END::DOUBLE AS y, " + ", ".join(f"x{i}" for i in range(D)) + " FROM charge WHERE split = 'train')"]
    square = " + ".join(f"x{i} * x{i}" for i in range(D))
    out.append(f"geo AS (SELECT avg(q) * {0.25 if objective == 'logistic' else 1.0} + {2 * LAM} AS smooth FROM (SELECT avg({square}) AS q FROM pts GROUP BY worker_id))")
    out.append("w1 AS (SELECT " + _list(["0.0::DOUBLE"] * D) + " AS w)")
    mu = 2 * LAM
    for k in range(1, rounds + 2):
        out.append(_gradients(f"g{k}", f"w{k}", objective=objective).replace(f"g{k} AS (", f"g{k} AS MATERIALIZED (", 1))
        mean = _list(f"avg(g[{i + 1}])" for i in range(D))
        norm = "sqrt(" + " + ".join(f"g[{i + 1}] * g[{i + 1}]" for i in range(D)) + ")"
        out.append(f"s{k} AS (SELECT w, l, g, {norm} AS n FROM (SELECT avg(l) AS l, {mean} AS g FROM g{k}), w{k})")
        if spec.memory and k > 1:
            out.append(f"a{k} AS (SELECT CASE WHEN s.n <= b.n * (1 + 1e-12::DOUBLE) THEN s.w ELSE b.w END AS w, CASE WHEN s.n <= b.n * (1 + 1e-12::DOUBLE) THEN s.g ELSE b.g END AS g, least(s.n, b.n) AS n, s.n <= b.n * (1 + 1e-12::DOUBLE) AS ok FROM s{k} s, a{k - 1} b)")
            out.append(f"h{k} AS (SELECT c.worker_id, CASE WHEN a.ok THEN c.g ELSE o.g END AS g FROM g{k} c JOIN h{k - 1} o USING (worker_id), a{k} a)")
        else:
            out.append(f"a{k} AS (SELECT w, g, n, true AS ok FROM s{k})")
            out.append(f"h{k} AS (SELECT worker_id, g FROM g{k})")
        if k > rounds:
            break
        base = 1 if spec.lattice == "fixed" else k
        out.append(f"r{k} AS (SELECT {scale} * 2 * n / {mu} AS rw, smooth * {scale} * 2 * n / {mu} AS rg, w AS c FROM a{base}, geo)")
        q = p if spec.lattice else 0
        if spec.family == "gd":
            grads = f"SELECT {_round('h.g', 'f.g', 'r.rg', p, 'CONCAT(' + chr(39) + 'grad' + chr(39) + ', h.worker_id)', k, 1, seed)} AS g FROM h{k} h JOIN h{base} f USING (worker_id), r{k} r" if q else f"SELECT g FROM h{k}"
            out.append(f"q{k} AS (SELECT {mean} AS g FROM ({grads}))")
            moved = _list(f"a.w[{i + 1}] - {step} * q.g[{i + 1}]" for i in range(D))
            out.append(f"u{k} AS (SELECT {moved} AS w FROM a{k} a, q{k} q)")
        else:
            for t in range(1, (steps if spec.family == "avr" else 1) + 1):
                before = f"a{k}" if t == 1 else f"i{k}_{t - 1}"
                out.append(f"d{k}_{t} AS (SELECT CAST(floor({duck_uniform(chr(39) + f'{seed}|worker|{k}|{t}|0' + chr(39))} * {N}) AS INTEGER) AS xi)")
                out.append(_gradients(f"c{k}_{t}", before, f", d{k}_{t} WHERE p.worker_id = xi", objective))
                new, old = "c.g", "h.g"
                if q and (spec.family != "avr" or spec.inner == "both"):
                    new = _round("c.g", "f.g", "r.rg", p, "CONCAT('grad', h.worker_id)", k, t, seed)
                if q and spec.family == "avr" and spec.inner in ("anchor", "both"):
                    old = _round("h.g", "f.g", "r.rg", p, "CONCAT('anchorgrad', h.worker_id)", k, t, seed)
                out.append(f"v{k}_{t} AS (SELECT h.worker_id, {new} AS new, {old} AS old FROM c{k}_{t} c JOIN h{k} h USING (worker_id) JOIN h{base} f USING (worker_id), r{k} r)")
                if spec.family == "avr":
                    moved = _list(f"b.w[{i + 1}] - {step} * (v.new[{i + 1}] - v.old[{i + 1}] + a.g[{i + 1}])" for i in range(D))
                    out.append(f"m{k}_{t} AS (SELECT {moved} AS w FROM {before} b, v{k}_{t} v, a{k} a)")
                    made = _round("m.w", "r.c", "r.rw", p, "'model'", k, t, seed) if q else "m.w"
                    out.append(f"i{k}_{t} AS MATERIALIZED (SELECT {made} AS w FROM m{k}_{t} m, r{k} r)")
            if spec.family == "avr":
                picks = f"CAST(floor({duck_uniform(chr(39) + f'{seed}|pick|{k}|0|0' + chr(39))} * {steps}) AS INTEGER)"
                kept = " UNION ALL ".join([f"SELECT 0 AS t, w FROM a{k}", *[f"SELECT {t}, w FROM i{k}_{t}" for t in range(1, steps)]])
                out.append(f"w{k + 1} AS MATERIALIZED (SELECT w FROM ({kept}) WHERE t = {picks})")
                continue
            if spec.family == "sag":
                was = f"b{k - 1}" if k > 1 else f"(SELECT worker_id, {_list(['0.0::DOUBLE'] * D)} AS g FROM h1)"
                out.append(f"b{k} AS MATERIALIZED (SELECT o.worker_id, CASE WHEN v.worker_id = o.worker_id THEN v.new ELSE o.g END AS g FROM {was} o, v{k}_1 v)")
                out.append(f"q{k} AS (SELECT {mean} AS g FROM b{k})")
            else:
                out.append(f"q{k} AS (SELECT new AS g FROM v{k}_1)")
            moved = _list(f"a.w[{i + 1}] - {step} * q.g[{i + 1}]" for i in range(D))
            out.append(f"u{k} AS (SELECT {moved} AS w FROM a{k} a, q{k} q)")
        made = _round("u.w", "r.c", "r.rw", p, "'model'", k, 1, seed) if q else "u.w"
        out.append(f"w{k + 1} AS MATERIALIZED (SELECT {made} AS w FROM u{k} u, r{k} r)")
    rows = " UNION ALL ".join(f"SELECT {k} AS k, round(s.l, 6) AS loss, round(s.n, 6) AS grad_norm, a.ok AS accepted FROM s{k} s, a{k} a" for k in range(1, rounds + 2))
    return "WITH " + ",\n".join(out) + f"\n{rows}"


def settings_sql(method: str, rounds: int, steps: int, seed: int, settings: dict[str, tuple[int, float]], objective: str = "logistic") -> str:
    """The runs of a method at several settings {name: (bits, step)}, one below the other."""
    parts = (f"SELECT '{name}' AS setting, * FROM ({method_sql(method, rounds, steps, step, p, seed, objective=objective)})" for name, (p, step) in settings.items())
    return "\nUNION ALL\n".join(parts)
