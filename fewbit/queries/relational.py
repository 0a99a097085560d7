"""The relational operators around the methods, each beside its SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from fewbit.functions.theory import best_step_sql, epoch_sql
from fewbit.sources import load


def _t(name):
    return lambda spark, sf_dir: load(spark, sf_dir, name)


lineitem, orders, part, customer, events, documents, labels, embeddings = map(_t, "lineitem orders part customer events documents labels embeddings".split())


def join_broadcast(s, d):
    return lineitem(s, d).join(F.broadcast(load(s, d, "nation")), F.pmod("l_suppkey", F.lit(25)) == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


def join_merge(s, d):
    o = orders(s, d).hint("merge")
    return lineitem(s, d).join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"))


def join_shuffled_hash(s, d):
    o = orders(s, d).hint("shuffle_hash")
    return lineitem(s, d).join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.countDistinct("l_orderkey").alias("n"))


def join_outer(s, d):
    a = lineitem(s, d).groupBy(F.col("l_partkey").alias("k")).agg(F.count("*").alias("n"))
    b = part(s, d).where("p_size > 25").select(F.col("p_partkey").alias("k"), "p_size")
    return a.join(b, "k", "full").select("k", "n", "p_size")


def join_semi_anti(s, d):
    docs, lab = documents(s, d).select("doc_id", "lang"), labels(s, d).select("doc_id")
    has = docs.join(lab, "doc_id", "left_semi").withColumn("labelled", F.lit(True))
    return has.unionByName(docs.join(lab, "doc_id", "left_anti").withColumn("labelled", F.lit(False))).groupBy("lang", "labelled").agg(F.count("*").alias("n"))


def join_self(s, d):
    e = events(s, d).groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    a, b = e.alias("a"), e.alias("b")
    return a.join(b, (F.col("a.user_id") == F.col("b.user_id")) & (F.col("a.event_type") < F.col("b.event_type"))).groupBy(F.col("a.event_type").alias("one"), F.col("b.event_type").alias("other")).agg(F.count("*").alias("users"))


def join_asof(s, d):
    """Each event with the user's latest earlier event of value above 50: a union and a window, no range join."""
    e = events(s, d).select("event_id", "user_id", "ts", "value")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return e.withColumn("seen", F.last(F.when(F.col("value") > 50, F.col("event_id")), ignorenulls=True).over(w)).select("event_id", "seen")


def join_interval(s, d):
    """Events by bins of value: the first and last bin are open, and values that no bin takes (null, NaN) have a row without bin."""
    lo = F.col("id") * 10
    days = s.range(-1, 41).select(F.when(F.col("id") < 0, float("-inf")).otherwise(lo).alias("lo"), F.when(F.col("id") == 40, float("inf")).otherwise(lo + 10).alias("hi"))
    e = events(s, d)
    inside = (e.value >= days.lo) & ((e.value < days.hi) | ((days.hi == float("inf")) & ~F.isnan(e.value)))
    return e.join(F.broadcast(days), inside, "left").groupBy("lo").agg(F.count("*").alias("n"))


def agg_partial(s, d):
    return lineitem(s, d).groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("q"), F.round(F.avg("l_extendedprice"), 4).alias("p"), F.count("*").alias("n"))


def agg_salted(s, d):
    """Two-level sums: a hot key is first summed by a salt of its rows."""
    salt = F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(16))
    first = lineitem(s, d).groupBy("l_returnflag", salt.alias("salt")).agg(F.sum("l_quantity").alias("q"), F.count("*").alias("n"))
    return first.groupBy("l_returnflag").agg(F.round(F.sum("q"), 2).alias("q"), F.sum("n").alias("n"))


def agg_sorted_lists(s, d):
    return events(s, d).groupBy("user_id").agg(F.array_sort(F.collect_list("event_id")).alias("ids")).select("user_id", F.size("ids").alias("n"), F.element_at("ids", 1).alias("first"), F.element_at("ids", -1).alias("last"))


def agg_distinct(s, d):
    return events(s, d).groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.count("*").alias("n"))


def agg_rollup(s, d):
    return lineitem(s, d).rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


def agg_cube(s, d):
    return lineitem(s, d).cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


def agg_grouping_sets(s, d):
    lineitem(s, d).createOrReplaceTempView("fb_lineitem")
    return s.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM fb_lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")


def agg_pivot(s, d):
    return events(s, d).groupBy(F.pmod("user_id", F.lit(10)).alias("worker")).pivot("event_type", ["click", "view", "purchase"]).agg(F.count(F.lit(1)))


def agg_unpivot(s, d):
    wide = lineitem(s, d).groupBy("l_returnflag").agg(F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.sum("l_tax"), 4).alias("tax"))
    return wide.unpivot("l_returnflag", ["quantity", "tax"], "measure", "value")


def agg_statistics(s, d):
    return lineitem(s, d).groupBy("l_returnflag").agg(
        F.round(F.stddev("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.covar_pop("l_tax", "l_discount"), 9).alias("cov"),
        F.median("l_quantity").alias("median"), F.max_by("l_linenumber", F.struct("l_extendedprice", "l_orderkey", "l_linenumber")).alias("of_max"), F.bool_and(F.col("l_tax") >= 0).alias("ok"),
    )


def window_ranking(s, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return customer(s, d).select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"))


def window_analytic(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events(s, d).select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(w).alias("second"))


def window_cumulative(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events(s, d).select("event_id", F.count("*").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("k"), F.round(F.avg("value").over(w.rowsBetween(-4, 0)), 6).alias("moving"))


def window_range(s, d):
    w = Window.partitionBy("user_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-86400, 0)
    return events(s, d).select("event_id", F.count("*").over(w).alias("day"))


def top_k(s, d):
    return lineitem(s, d).select("l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey").limit(20)


def top_k_by_group(s, d):
    w = Window.partitionBy("label").orderBy(F.desc(F.abs(F.col("embedding")[0])), "vec_id")
    return embeddings(s, d).withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("label", "vec_id", "rn")


def set_operations(s, d):
    a, b = lineitem(s, d).select(F.col("l_partkey").alias("k")), part(s, d).where("p_size < 25").select(F.col("p_partkey").alias("k"))
    parts = [("intersect", a.intersect(b)), ("except", a.select("k").distinct().exceptAll(b)), ("union", a.union(b).distinct())]
    made = [x.agg(F.lit(n).alias("op"), F.count("*").alias("n"), F.sum("k").alias("total")) for n, x in parts]
    return made[0].unionByName(made[1]).unionByName(made[2])


def sample_by_hash(s, d):
    return lineitem(s, d).where(F.expr("CAST(conv(substring(md5(CAST(l_orderkey AS STRING)), 1, 8), 16, 10) AS BIGINT) % 10 = 3")).groupBy("l_returnflag").agg(F.count("*").alias("n"))


def dedup_text(s, d):
    return documents(s, d).groupBy(F.md5("text").alias("h")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies"))


def subqueries(s, d):
    lineitem(s, d).createOrReplaceTempView("fb_lineitem")
    orders(s, d).createOrReplaceTempView("fb_orders")
    return s.sql(
        "SELECT o_orderpriority, count(*) AS n FROM fb_orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM fb_orders) "
        "AND EXISTS (SELECT 1 FROM fb_lineitem l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > :q) GROUP BY o_orderpriority",
        args={"q": 45.0},
    )


def string_functions(s, d):
    t = F.col("text")
    return documents(s, d).select("doc_id", F.length(F.lower(t)).alias("n"), F.regexp_count(t, F.lit("[aeiou]")).alias("vowels"), F.size(F.split(t, " ")).alias("parts"), F.lpad(F.conv(F.substring(F.md5(t), 1, 4), 16, 2), 16, "0").alias("bits"))


def date_functions(s, d):
    t = F.col("ts")
    return events(s, d).select("event_id", F.month(t).alias("m"), (F.dayofweek(t) - 1).alias("dow"), F.hour(t).alias("h"), F.date_format(F.date_trunc("day", t), "yyyy-MM-dd").alias("day"), F.unix_timestamp(t).alias("s"))


def math_functions(s, d):
    v = F.col("value")
    return events(s, d).select("event_id", F.round(F.log1p(v), 6).alias("l"), F.floor(v).alias("f"), F.ceil(v).alias("c"), F.round(F.sqrt(v), 6).alias("q"), F.greatest(v, F.lit(10.0)).alias("g"), F.pmod(F.col("event_id"), F.lit(7)).alias("m"), F.signum(v - 35).alias("sg"))


def array_functions(s, d):
    x = F.col("x")
    e = embeddings(s, d).select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    dot = F.aggregate(F.zip_with(x, F.reverse(x), lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)
    return e.select("vec_id", F.round(dot, 9).alias("dot"), F.array_position(x, F.array_max(x)).alias("argmax"), F.size(F.filter(x, lambda v: v > 0)).alias("positive"), F.exists(x, lambda v: v > 0.4).alias("large"), F.size(F.slice(x, 2, 5)).alias("five"))


def map_json_functions(s, d):
    e = events(s, d)
    m = F.from_json("props", "map<string,string>")
    return e.select("event_id", F.size(F.map_keys(m)).alias("keys"), F.array_join(F.array_sort(F.map_keys(m)), ",").alias("names"))


def null_handling(s, d):
    lab = documents(s, d).join(labels(s, d), "doc_id", "left")
    return lab.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("q"), F.col("quality").eqNullSafe(F.lit(None).cast("int")).alias("none"))


def grouped_arrow(s, d):
    """A worker's mean vector by grouped Arrow batches: one shard, one call; a row for each coordinate."""
    import numpy as np
    import pyarrow as pa

    def mean(key, t):
        x = t.column("embedding").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(t.num_rows, -1).astype(float).mean(0)
        return pa.table({"worker": [key[0].as_py()] * len(x), "n": [t.num_rows] * len(x), "dim": np.arange(len(x), dtype=np.int32), "m": np.round(x, 6) + 0.0})

    e = embeddings(s, d).select(F.pmod("vec_id", F.lit(10)).alias("worker"), "embedding")
    return e.groupBy("worker").applyInArrow(mean, "worker long, n long, dim int, m double")


def grouped_aggregate(s, d):
    """A grouped aggregate function in Python: the spread of a user's readings around their median."""
    @F.pandas_udf("double", F.PandasUDFType.GROUPED_AGG)
    def spread(v):
        return float((v - v.median()).abs().mean())

    return events(s, d).groupBy("user_id").agg(spread("value").alias("s")).select("user_id", F.round("s", 6).alias("spread"))


def agg_percentiles(s, d):
    """Discrete percentiles by a sketch with more room than a group has rows, so that they are exact on small groups."""
    return events(s, d).groupBy("user_id").agg(*[F.percentile_approx("value", q, 100_000).alias(f"p{int(100 * q)}") for q in (0.1, 0.5, 0.9)])


def agg_histogram(s, d):
    """Ten adaptive bins of the readings; their heights add up to the rows."""
    h = events(s, d).agg(F.histogram_numeric("value", F.lit(10)).alias("h"))
    return h.select(F.size("h").alias("bins"), F.expr("CAST(aggregate(h, 0D, (a, b) -> a + b.y) AS BIGINT)").alias("n"))


def sample_stratified(s, d):
    """Every row of the classes taken whole, none of those left out: the ends of stratified sampling, which are certain."""
    e = events(s, d)
    return e.sampleBy("event_type", {"click": 1.0, "view": 1.0, "purchase": 0.0}, seed=7).groupBy("event_type").agg(F.count("*").alias("n"))


TARGETS = "SELECT CAST(l_linenumber AS DOUBLE) / 8 AS target, count(*) AS items FROM lineitem GROUP BY ALL"


def _targets(s, d):
    """A target a line number, with the number of its line items."""
    return load(s, d, "lineitem").groupBy((F.col("l_linenumber").cast("double") / 8).alias("target")).agg(F.count("*").alias("items"))


def bounds_table_function(s, d):
    """A Python table function: the epoch lengths for a target over numbers of bits, with the best step of each."""
    from pyspark.sql.functions import udtf

    from fewbit.functions import theory

    @udtf(returnType="p int, step double, epoch double")
    class EpochBounds:
        def eval(self, target: float, smooth: float, mu: float, dim: int, low: int, high: int):
            for p in range(low, high + 1):
                a = theory.best_step(target, smooth, mu, dim, p)
                t = theory.epoch_for_target(target, smooth, mu, a, dim, p)
                yield p, round(a, 9), None if t == float("inf") else round(t, 4)

    s.udtf.register("epoch_bounds", EpochBounds)
    _targets(s, d).createOrReplaceTempView("fb_targets")
    return s.sql("SELECT target, items, p, step, epoch FROM fb_targets, LATERAL epoch_bounds(target, 0.967D, 0.2D, 9, 6, 20)")


def library_optimum(s, d):
    """The optimum of the charge task by the ML library's logistic regression, beside ours: both are the same model."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector

    from fewbit.operators import tasks
    from fewbit.plans.driver import reference_optimum

    # the library gives constant features no weight; its penalty has a half, and it weighs samples alike
    pts = tasks.charge(s, d).where("split = 'train'").withColumn("x", F.slice("x", 1, 8)).persist()
    model = LogisticRegression(regParam=0.2, fitIntercept=False, standardization=False, tol=1e-7, maxIter=200).fit(pts.select(array_to_vector("x").alias("features"), F.col("cls").cast("double").alias("label")))
    own, _, _ = reference_optimum(pts, 8, engine="measured", weighting="sample")
    pts.unpersist()
    rows = [(i, bool(abs(a - b) < 1e-4)) for i, (a, b) in enumerate(zip(model.coefficients.toArray(), own, strict=True))]
    return s.createDataFrame(rows, "dim int, same boolean")


def cogrouped(s, d):
    """Shards beside a table of stored state, by worker."""
    import pandas as pd

    def meet(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"worker": [int(a["worker"].iloc[0] if len(a) else b["worker"].iloc[0])], "rows": [len(a)], "state": [float(b["state"].sum())]})

    a = events(s, d).select(F.pmod("user_id", F.lit(10)).alias("worker"), "value")
    b = s.range(12).select(F.col("id").alias("worker"), (F.col("id") * 0.5).alias("state"))
    return a.groupBy("worker").cogroup(b.groupBy("worker")).applyInPandas(meet, "worker long, rows long, state double")


def table_function(s, d):
    """A Python table function in SQL: the points of a lattice."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="j int, point double")
    class LatticePoints:
        def eval(self, center: float, radius: float, bits: int):
            top = 2**bits - 1
            for j in range(top + 1):
                yield j, round(center - radius + j * (2 * radius / top), 9)

    s.udtf.register("lattice_points", LatticePoints)
    _targets(s, d).createOrReplaceTempView("fb_targets")
    return s.sql("SELECT target, items, j, point FROM fb_targets, LATERAL lattice_points(target, 2.0D, 4)")


def sql_functions(s, d):
    """The library's functions, registered for SQL."""
    from fewbit.functions.sqlfn import register_functions

    register_functions(s)
    embeddings(s, d).createOrReplaceTempView("fb_vectors")
    return s.sql("SELECT vec_id, octet_length(fb_pack(transform(embedding, v -> bigint(greatest(least((v + 0.5) * 31, 31), 0))), 5)) AS bytes, round(fb_epoch_min(0.5D, 0.967D, 0.2D, 0.07D, 9, 15), 4) AS t FROM fb_vectors")


def prediction(s, d):
    """Scores of three fixed linear models over all coordinates and the class of the largest, of equals the smallest class."""
    e = embeddings(s, d).select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    score = lambda c: F.expr(f"aggregate(transform(x, (v, i) -> v * ((i * {2 * c + 3}) % 7 - 3)), 0D, (a, b) -> a + b)")
    best = F.array_max(F.array(*[F.struct(F.round(score(c), 9).alias("s"), F.lit(-c).alias("c")) for c in range(3)]))
    return e.select("vec_id", (-best["c"]).alias("cls"))


QUERIES = {f"op_{f.__name__}": f for f in (
    join_broadcast, join_merge, join_shuffled_hash, join_outer, join_semi_anti, join_self, join_asof, join_interval, agg_partial, agg_salted, agg_sorted_lists, agg_distinct, agg_rollup, agg_cube,
    agg_grouping_sets, agg_pivot, agg_unpivot, agg_statistics, window_ranking, window_analytic, window_cumulative, window_range, top_k, top_k_by_group, set_operations, sample_by_hash, dedup_text,
    subqueries, string_functions, date_functions, math_functions, array_functions, map_json_functions, null_handling, grouped_arrow, grouped_aggregate, agg_percentiles, agg_histogram, sample_stratified, bounds_table_function, library_optimum, cogrouped, table_function, sql_functions, prediction,
)}
_W = "PARTITION BY user_id ORDER BY ts, event_id"
ORACLES = {
    "op_join_broadcast": "SELECT n_name, count(*) AS n FROM lineitem JOIN nation ON l_suppkey % 25 = n_nationkey GROUP BY n_name",
    "op_join_merge": "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL",
    "op_join_shuffled_hash": "SELECT o_orderstatus, count(DISTINCT l_orderkey) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL",
    "op_join_outer": "SELECT k, n, p_size FROM (SELECT l_partkey AS k, count(*) AS n FROM lineitem GROUP BY 1) FULL JOIN (SELECT p_partkey AS k, p_size FROM part WHERE p_size > 25) USING (k)",
    "op_join_semi_anti": "SELECT lang, doc_id IN (SELECT doc_id FROM labels) AS labelled, count(*) AS n FROM documents GROUP BY ALL",
    "op_join_self": "WITH e AS (SELECT DISTINCT user_id, event_type FROM events) SELECT a.event_type AS one, b.event_type AS other, count(*) AS users FROM e a JOIN e b ON a.user_id = b.user_id AND a.event_type < b.event_type GROUP BY ALL",
    "op_join_asof": f"SELECT event_id, last_value(CASE WHEN value > 50 THEN event_id END IGNORE NULLS) OVER ({_W} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM events",
    "op_join_interval": "SELECT CASE WHEN value < 0 THEN '-Infinity'::DOUBLE WHEN value >= 400 AND NOT isnan(value) THEN 400.0 WHEN NOT isnan(value) THEN floor(value / 10) * 10 END AS lo, count(*) AS n FROM events GROUP BY 1",
    "op_agg_partial": "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS q, round(avg(l_extendedprice), 4) AS p, count(*) AS n FROM lineitem GROUP BY ALL",
    "op_agg_salted": "SELECT l_returnflag, round(sum(l_quantity), 2) AS q, count(*) AS n FROM lineitem GROUP BY ALL",
    "op_agg_sorted_lists": "SELECT user_id, CAST(count(*) AS INTEGER) AS n, min(event_id) AS first, max(event_id) AS last FROM events GROUP BY ALL",
    "op_agg_distinct": "SELECT event_type, count(DISTINCT user_id) AS users, count(*) AS n FROM events GROUP BY ALL",
    "op_agg_rollup": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "op_agg_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "op_agg_grouping_sets": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
    "op_agg_pivot": "SELECT user_id % 10 AS worker, nullif(count(*) FILTER (event_type = 'click'), 0) AS click, nullif(count(*) FILTER (event_type = 'view'), 0) AS view, nullif(count(*) FILTER (event_type = 'purchase'), 0) AS purchase FROM events GROUP BY 1",
    "op_agg_unpivot": "SELECT l_returnflag, 'quantity' AS measure, round(sum(l_quantity), 2) AS value FROM lineitem GROUP BY 1 UNION ALL SELECT l_returnflag, 'tax', round(sum(l_tax), 4) FROM lineitem GROUP BY 1",
    "op_agg_statistics": "SELECT l_returnflag, round(stddev(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_pop(l_tax, l_discount), 9) AS cov, median(l_quantity) AS median, arg_max(l_linenumber, (l_extendedprice, l_orderkey, l_linenumber)) AS of_max, bool_and(l_tax >= 0) AS ok FROM lineitem GROUP BY 1",
    "op_window_ranking": "SELECT c_custkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr, CAST(ntile(4) OVER w AS INTEGER) AS nt, round(percent_rank() OVER w, 6) AS pr FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)",
    "op_window_analytic": f"SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS ({_W})",
    "op_window_cumulative": f"SELECT event_id, count(*) OVER ({_W} ROWS UNBOUNDED PRECEDING) AS k, round(avg(value) OVER ({_W} ROWS 4 PRECEDING), 6) AS moving FROM events",
    "op_window_range": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day FROM events",
    "op_top_k": "SELECT l_orderkey, l_linenumber, l_partkey, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey LIMIT 20",
    "op_top_k_by_group": "SELECT label, vec_id, CAST(rn AS INTEGER) AS rn FROM (SELECT label, vec_id, row_number() OVER (PARTITION BY label ORDER BY abs(embedding[1]) DESC, vec_id) AS rn FROM embeddings) WHERE rn <= 3",
    "op_set_operations": "WITH a AS (SELECT l_partkey AS k FROM lineitem), b AS (SELECT p_partkey AS k FROM part WHERE p_size < 25) SELECT 'intersect' AS op, count(*) AS n, CAST(sum(k) AS BIGINT) AS total FROM (SELECT k FROM a INTERSECT SELECT k FROM b) UNION ALL SELECT 'except', count(*), CAST(sum(k) AS BIGINT) FROM (SELECT k FROM a EXCEPT SELECT k FROM b) UNION ALL SELECT 'union', count(*), CAST(sum(k) AS BIGINT) FROM (SELECT k FROM a UNION SELECT k FROM b)",
    "op_sample_by_hash": "SELECT l_returnflag, count(*) AS n FROM lineitem WHERE ('0x' || substr(md5(l_orderkey::VARCHAR), 1, 8))::BIGINT % 10 = 3 GROUP BY 1",
    "op_dedup_text": "SELECT md5(text) AS h, min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY 1",
    "op_subqueries": "SELECT o_orderpriority, count(*) AS n FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders) AND o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45) GROUP BY 1",
    "op_string_functions": "SELECT doc_id, CAST(length(lower(text)) AS INTEGER) AS n, CAST(len(regexp_extract_all(text, '[aeiou]')) AS INTEGER) AS vowels, CAST(len(string_split(text, ' ')) AS INTEGER) AS parts, lpad(bin(('0x' || substr(md5(text), 1, 4))::BIGINT), 16, '0') AS bits FROM documents",
    "op_date_functions": "SELECT event_id, CAST(month(ts) AS INTEGER) AS m, CAST(dayofweek(ts) AS INTEGER) AS dow, CAST(hour(ts) AS INTEGER) AS h, strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, CAST(floor(epoch(ts)) AS BIGINT) AS s FROM events",
    "op_math_functions": "SELECT event_id, round(ln(1 + value), 6) AS l, CAST(floor(value) AS BIGINT) AS f, CAST(ceil(value) AS BIGINT) AS c, round(sqrt(value), 6) AS q, greatest(value, 10.0::DOUBLE) AS g, event_id % 7 AS m, CAST(sign(value - 35) AS DOUBLE) AS sg FROM events",
    "op_array_functions": "SELECT vec_id, round(list_sum(list_transform(range(1, 65), lambda i: embedding[i]::DOUBLE * embedding[65 - i]::DOUBLE)), 9) AS dot, CAST(list_position(embedding, list_max(embedding)) AS BIGINT) AS argmax, CAST(len(list_filter(embedding, lambda v: v > 0)) AS INTEGER) AS positive, len(list_filter(embedding, lambda v: v::DOUBLE > 0.4)) > 0 AS large, 5::INTEGER AS five FROM embeddings",
    "op_map_json_functions": "SELECT event_id, CAST(len(json_keys(props)) AS INTEGER) AS keys, array_to_string(list_sort(json_keys(props)), ',') AS names FROM events",
    "op_null_handling": "SELECT doc_id, coalesce(quality, -1) AS q, quality IS NULL AS none FROM documents LEFT JOIN labels USING (doc_id)",
    "op_grouped_arrow": "SELECT vec_id % 10 AS worker, n, dim, round(m, 6) + 0.0::DOUBLE AS m FROM (SELECT vec_id % 10 AS vec_id, count(*) AS n, CAST(i - 1 AS INTEGER) AS dim, avg(embedding[i]::DOUBLE) AS m FROM embeddings, range(1, 65) r(i) GROUP BY vec_id % 10, i)",
    "op_grouped_aggregate": "SELECT user_id, round(avg(abs(value - m)), 6) AS spread FROM events JOIN (SELECT user_id, median(value) AS m FROM events GROUP BY 1) USING (user_id) GROUP BY user_id",
    "op_agg_percentiles": "SELECT user_id, quantile_disc(value, 0.1) AS p10, quantile_disc(value, 0.5) AS p50, quantile_disc(value, 0.9) AS p90 FROM events GROUP BY 1",
    "op_agg_histogram": "SELECT 10::INTEGER AS bins, count(*) AS n FROM events",
    "op_sample_stratified": "SELECT event_type, count(*) AS n FROM events WHERE event_type IN ('click', 'view') GROUP BY 1",
    "op_bounds_table_function": "SELECT target, items, p, round(a, 9) AS step, round(" + epoch_sql("target", "0.967::DOUBLE", "0.2::DOUBLE", "a", "9.0::DOUBLE", "p") + ", 4) AS epoch FROM (SELECT target, items, p, " + best_step_sql("target", "0.967::DOUBLE", "0.2::DOUBLE", "9.0::DOUBLE", "p") + f" AS a FROM ({TARGETS}), (SELECT unnest(range(6, 21))::INTEGER AS p))",
    "op_sql_functions": "SELECT vec_id, 40::INTEGER AS bytes, round(" + epoch_sql("0.5::DOUBLE", "0.967::DOUBLE", "0.2::DOUBLE", "0.07::DOUBLE", "9.0::DOUBLE", "15") + ", 4) AS t FROM embeddings",
    "op_cogrouped": "SELECT worker, coalesce(n, 0) AS rows, coalesce(state, 0) AS state FROM (SELECT user_id % 10 AS worker, count(*) AS n FROM events GROUP BY 1) FULL JOIN (SELECT i AS worker, i * 0.5::DOUBLE AS state FROM range(12) r(i)) USING (worker)",
    "op_table_function": f"SELECT target, items, CAST(j AS INTEGER) AS j, round(target - 2.0::DOUBLE + j * (4.0::DOUBLE / 15), 9) AS point FROM ({TARGETS}), range(16) r(j)",
    "op_prediction": "SELECT vec_id, CAST(CASE WHEN a >= b AND a >= c THEN 0 WHEN b >= c THEN 1 ELSE 2 END AS INTEGER) AS cls FROM (SELECT vec_id, "
    + ", ".join(f"round(list_sum(list_transform(range(0, 64), lambda i: embedding[i + 1]::DOUBLE * ((i * {2 * c + 3}) % 7 - 3))), 9) AS {n}" for c, n in enumerate("abc"))
    + " FROM embeddings)",
}
