"""Registered queries of the surrounding operators: sources, design, joins, aggregates, windows, functions, UDFs, streams."""

from __future__ import annotations


from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tallquant.functions import loss as L
from tallquant.functions import randomness as rnd
from tallquant.functions import udfs
from tallquant.operators import quantreg, sampling
from tallquant.operators import relational as rel
from tallquant.plans.catalog import CAUCHY_SQL, PAIRS_SQL, R, SEED, pin_sql, query, significant, significant_sql, sketch_sql
from tallquant.sources import design as D
from tallquant.sources import skew_source, storage
from tallquant.streaming import streams

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def t(spark, sf_dir: str, name: str) -> DataFrame:
    return D.table(spark, sf_dir, name)


# --- sources and sinks ---------------------------------------------------------------


@query(" UNION ALL ".join(f"SELECT '{n}' AS name, count(*) AS n FROM {n}" for n in TABLES))
def src_scan_counts(spark, sf_dir):
    out = None
    for n in TABLES:
        part = t(spark, sf_dir, n).agg(F.count("*").alias("n")).select(F.lit(n).alias("name"), "n")
        out = part if out is None else out.union(part)
    return out


@query("SELECT 'csv' AS fmt, count(*) AS n FROM nation UNION ALL SELECT 'json', count(*) FROM nation UNION ALL SELECT 'orc', count(*) FROM nation")
def src_schema_roundtrip(spark, sf_dir):
    nation, out = t(spark, sf_dir, "nation"), None
    for fmt in ("csv", "json", "orc"):
        same = storage.round_trip(nation, fmt).intersect(nation).agg(F.count("*").alias("n")).select(F.lit(fmt).alias("fmt"), "n")
        out = same if out is None else out.union(same)
    return out


@query("SELECT count(*) AS n, count(*) FILTER (n_regionkey < 2) AS with_region, sum(n_nationkey)::bigint AS keys FROM nation")
def src_merged_schema(spark, sf_dir):
    """Files of different columns read as one table: absent columns are null."""
    nation, path = t(spark, sf_dir, "nation"), storage.scratch(spark, "merged")
    nation.where("n_regionkey < 2").write.parquet(path)
    nation.where("n_regionkey >= 2").drop("n_regionkey").write.mode("append").parquet(path)
    merged = spark.read.option("mergeSchema", True).parquet(path)
    return merged.agg(F.count("*").alias("n"), F.count("n_regionkey").alias("with_region"), F.sum("n_nationkey").cast("long").alias("keys"))


@query("SELECT count(*) AS n, sum(length(n_name))::bigint AS letters FROM nation")
def src_text_lines(spark, sf_dir):
    path = storage.scratch(spark, "text")
    t(spark, sf_dir, "nation").select("n_name").write.text(path)
    return spark.read.text(path).agg(F.count("*").alias("n"), F.sum(F.length("value")).cast("long").alias("letters"))


@query("SELECT typeof(n_nationkey) IN ('INTEGER', 'BIGINT') AS whole, count(*) AS n FROM nation GROUP BY 1")
def src_inferred_schema(spark, sf_dir):
    path = storage.scratch(spark, "inferred")
    t(spark, sf_dir, "nation").write.option("header", True).csv(path)
    read = spark.read.option("header", True).option("inferSchema", True).csv(path)
    return read.agg(F.count("*").alias("n")).select(F.lit(dict(read.dtypes)["n_nationkey"] in ("int", "bigint")).alias("whole"), "n")


@query("SELECT year(o_orderdate) AS yr, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders WHERE year(o_orderdate) = 1997 GROUP BY 1")
def src_partitioned_sink(spark, sf_dir):
    path = storage.write_partitioned(t(spark, sf_dir, "orders").withColumn("yr", F.year("o_orderdate")), "yr", "orders")
    return spark.read.parquet(path).where("yr = 1997").groupBy(F.col("yr").cast("long").alias("yr")).agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query(f"SELECT round(sum({pin_sql('value - 40', 0.75)}), 4) AS loss FROM events WHERE event_type = 'click'")
def src_sql_named_args(spark, sf_dir):
    t(spark, sf_dir, "events").createOrReplaceTempView("tallquant_events")
    return spark.sql("SELECT round(sum(greatest(:tau * (value - :m), (:tau - 1) * (value - :m))), 4) AS loss FROM tallquant_events WHERE event_type = :kind", args={"tau": 0.75, "m": 40.0, "kind": "click"})


@query("SELECT tau, event_type, count(*) AS n FROM events, (VALUES (0.25::double), (0.5), (0.75)) AS g(tau) GROUP BY ALL")
def src_grid_values(spark, sf_dir):
    grid = spark.sql("SELECT * FROM VALUES (0.25D), (0.5D), (0.75D) AS g(tau)")
    return t(spark, sf_dir, "events").crossJoin(F.broadcast(grid)).groupBy("tau", "event_type").agg(F.count("*").alias("n"))


@query(f"SELECT j, count(*) AS n, round(sum(b), 4) AS total, round(avg(v), 2) AS price FROM (SELECT j, b, v FROM ({D.skew_sql(5, 2.0, source='range(2000) AS r(i)', row_id='i::varchar')}) JOIN (SELECT (((o_orderkey % 2000) + 2000) % 2000)::varchar AS row_id, o_totalprice AS v FROM orders) USING (row_id)) GROUP BY j")
def src_python_datasource(spark, sf_dir):
    """Every order with the generated row of its number."""
    D.ship(spark)
    skew_source.register(spark)
    rows = spark.read.format("tallquant_skew").options(rows=2000, d=5, q=2.0, seed=3).load()
    orders = t(spark, sf_dir, "orders").select(F.pmod("o_orderkey", F.lit(2000)).cast("string").alias("row_id"), F.col("o_totalprice").alias("v"))
    return orders.join(rows, "row_id").groupBy("j").agg(F.count("*").alias("n"), F.round(F.sum("b"), 4).alias("total"), F.round(F.avg("v"), 2).alias("price"))


@query("SELECT c_nationkey, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def src_bucketed_join(spark, sf_dir):
    a = storage.write_bucketed(t(spark, sf_dir, "orders").select("o_orderkey", F.col("o_custkey").alias("k")), "k", "tallquant_orders_b")
    b = storage.write_bucketed(t(spark, sf_dir, "customer").select(F.col("c_custkey").alias("k"), "c_nationkey"), "k", "tallquant_customer_b")
    return a.join(b, "k").groupBy("c_nationkey").agg(F.count("*").alias("n"))


@query("SELECT count(*) AS n, round(sum(abs(s_acctbal)), 2) AS total FROM supplier")
def src_saved_fits(spark, sf_dir):
    path = storage.scratch(spark, "fits")
    storage.save_fits(t(spark, sf_dir, "supplier"), path)
    return storage.load_fits(spark, path).agg(F.count("*").alias("n"), F.round(F.sum(F.abs("s_acctbal")), 2).alias("total"))


# --- design ------------------------------------------------------------------------------


@query(f"SELECT count(*) AS n, {', '.join(f'round(sum(x[{j + 1}]), 4) AS s{j}' for j in range(11))} FROM ({D.census_sql()})")
def layout_coo_roundtrip(spark, sf_dir):
    design = D.census_design(spark, sf_dir)
    back = D.coo_to_dense(D.to_coo(design), 11)
    return back.agg(F.count("*").alias("n"), *[F.round(F.sum(F.col("x")[j]), 4).alias(f"s{j}") for j in range(11)])


@query(f"SELECT count(*) AS n, {', '.join(f'round(sum(x[{j + 1}]), 4) AS s{j}' for j in range(11))} FROM ({D.census_sql()})")
def layout_sparse_wide_roundtrip(spark, sf_dir):
    wide = D.to_wide(D.sparse_to_dense(D.to_sparse(D.census_design(spark, sf_dir)), 11), 11)
    return wide.agg(F.count("*").alias("n"), *[F.round(F.sum(f"x{j}"), 4).alias(f"s{j}") for j in range(11)])


@query("SELECT round(avg(l_quantity), 6) AS m1, round(stddev_pop(l_quantity), 6) AS d1, round(avg(l_quantity * l_quantity), 5) AS m2, round(avg(l_quantity * l_discount), 6) AS m3, round(avg(ln(l_extendedprice)), 6) AS mb FROM lineitem")
def design_formula(spark, sf_dir):
    line = t(spark, sf_dir, "lineitem")
    q = F.col("l_quantity")
    design = D.build(line, D.line_id(), F.log("l_extendedprice"), [F.lit(1.0), q, q * q, q * F.col("l_discount")])
    _, mean, scale = D.standardise(design)
    sums = design.agg(F.round(F.avg("b"), 6).alias("mb"))
    return sums.select(F.round(F.lit(mean[1]), 6).alias("m1"), F.round(F.lit(scale[1]), 6).alias("d1"), F.round(F.lit(mean[2]), 5).alias("m2"), F.round(F.lit(mean[3]), 6).alias("m3"), "mb")


@query("SELECT o_orderpriority AS priority, o_orderstatus AS status, count(*) AS n FROM orders GROUP BY ALL")
def design_onehot(spark, sf_dir):
    orders = t(spark, sf_dir, "orders")
    pr = [r[0] for r in orders.select("o_orderpriority").distinct().orderBy("o_orderpriority").collect()]
    st = [r[0] for r in orders.select("o_orderstatus").distinct().orderBy("o_orderstatus").collect()]
    cells = [(p * s).alias(f"c{i}_{k}") for i, p in enumerate(D.one_hot(F.col("o_orderpriority"), pr)) for k, s in enumerate(D.one_hot(F.col("o_orderstatus"), st))]
    total = orders.select(*cells).agg(*[F.sum(f"c{i}_{k}").alias(f"c{i}_{k}") for i in range(len(pr)) for k in range(len(st))])
    names = F.array(*[F.struct(F.lit(p).alias("priority"), F.lit(s).alias("status"), F.col(f"c{i}_{k}").cast("long").alias("n")) for i, p in enumerate(pr) for k, s in enumerate(st)])
    return total.select(F.explode(names).alias("r")).select("r.*").where("n > 0")


@query("SELECT year(l_shipdate) AS yr, count(*) AS n, sum(CASE WHEN year(l_shipdate) >= 1999 THEN 1 ELSE 0 END)::bigint AS late FROM lineitem GROUP BY 1")
def design_bands(spark, sf_dir):
    line = t(spark, sf_dir, "lineitem")
    return line.groupBy(F.year("l_shipdate").cast("long").alias("yr")).agg(F.count("*").alias("n"), F.sum(F.when(F.year("l_shipdate") >= 1999, 1).otherwise(0)).alias("late"))


@query("SELECT CASE WHEN s_acctbal < 0 THEN 0 WHEN s_acctbal >= 10000 THEN 6 ELSE floor(s_acctbal / 2000)::int + 1 END AS band, count(*) AS n FROM supplier GROUP BY 1")
def design_width_bucket(spark, sf_dir):
    band = F.expr("width_bucket(s_acctbal, 0, 10000, 5)").cast("int")
    return t(spark, sf_dir, "supplier").groupBy(band.alias("band")).agg(F.count("*").alias("n"))


@query("""SELECT j, sum(n)::bigint AS n, count(*) AS docs FROM (SELECT doc_id, ('0x' || substr(md5(w), 1, 8))::bigint % 16 AS j, count(*) AS n FROM (SELECT DISTINCT doc_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS w FROM documents) GROUP BY ALL) GROUP BY j""")
def design_hashed_tokens(spark, sf_dir):
    words = t(spark, sf_dir, "documents").select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0)))).alias("w"))
    slot = F.pmod(F.conv(F.substring(F.md5("w"), 1, 8), 16, 10).cast("long"), F.lit(16).cast("long"))
    return words.groupBy("doc_id", slot.alias("j")).agg(F.count("*").alias("n")).groupBy("j").agg(F.sum("n").alias("n"), F.count("*").alias("docs"))


@query("SELECT p_partkey, p_brand, p_size FROM part WHERE p_type LIKE 'S%' AND p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#11', 'Brand#23', 'Brand#34') OR p_retailprice IS NULL")
def filter_predicates(spark, sf_dir):
    c = F.col
    keep = (c("p_type").like("S%") & c("p_size").between(5, 20) & c("p_brand").isin("Brand#11", "Brand#23", "Brand#34")) | c("p_retailprice").isNull()
    return t(spark, sf_dir, "part").where(keep).select("p_partkey", "p_brand", "p_size")


@query("SELECT l_discount, l_tax, l_returnflag, count(*) AS n FROM lineitem GROUP BY ALL")
def distinct_collapse(spark, sf_dir):
    line = t(spark, sf_dir, "lineitem")
    keys = ["l_discount", "l_tax", "l_returnflag"]
    return line.select(*keys).distinct().join(line.groupBy(*keys).agg(F.count("*").alias("n")), keys)


@query(f"SELECT l_returnflag, count(*) AS n FROM (SELECT l_returnflag, {D.line_id_sql()} AS row_id FROM lineitem) WHERE {rnd.unit_sql(11, chr(39) + 'prefix' + chr(39), 'row_id')} < 0.1 GROUP BY 1")
def prefix_share(spark, sf_dir):
    rows = t(spark, sf_dir, "lineitem").select("l_returnflag", D.line_id().alias("row_id"))
    return D.prefix(rows, 0.1, engine="portable").groupBy("l_returnflag").agg(F.count("*").alias("n"))


@query("SELECT doc_id, nullif(quality, 0) AS q, coalesce(toxic, -1) AS tox, CASE WHEN n_chars > 1000 THEN 'long' ELSE 'short' END AS size FROM documents LEFT JOIN labels USING (doc_id)")
def conditional_nulls(spark, sf_dir):
    rows = t(spark, sf_dir, "documents").join(t(spark, sf_dir, "labels"), "doc_id", "left")
    return rows.select("doc_id", F.nullif("quality", F.lit(0)).alias("q"), F.coalesce("toxic", F.lit(-1)).alias("tox"), F.when(F.col("n_chars") > 1000, "long").otherwise("short").alias("size"))


# --- joins ------------------------------------------------------------------------------


@query(f"SELECT r_name, round(sum({pin_sql('l_extendedprice - 50000', 0.75)}), 4) AS loss, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def join_inner_star(spark, sf_dir):
    # nation and region have a fixed size; the rest is left to the optimizer
    geo = t(spark, sf_dir, "nation").join(F.broadcast(t(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    cust = t(spark, sf_dir, "customer").select("c_custkey", "c_nationkey").join(F.broadcast(geo), F.col("c_nationkey") == F.col("n_nationkey"))
    rows = t(spark, sf_dir, "lineitem").select("l_orderkey", "l_extendedprice").join(t(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).join(cust, F.col("o_custkey") == F.col("c_custkey"))
    return rows.groupBy("r_name").agg(F.round(F.sum(L.pinball(F.col("l_extendedprice") - 50000.0, 0.75)), 4).alias("loss"), F.count("*").alias("n"))


@query("SELECT quality IS NOT NULL AS labelled, count(*) AS n, quantile_cont(n_chars, 0.5) AS median FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1")
def join_outer_labels(spark, sf_dir):
    rows = t(spark, sf_dir, "documents").join(t(spark, sf_dir, "labels"), "doc_id", "left")
    return rows.groupBy(F.col("quality").isNotNull().alias("labelled")).agg(F.count("*").alias("n"), F.percentile("n_chars", 0.5).alias("median"))


@query("SELECT count(*) FILTER (l.doc_id IS NOT NULL) AS labelled, count(*) FILTER (l.doc_id IS NULL) AS unlabelled, count(*) FILTER (text NOT IN (SELECT text FROM benchmark)) AS not_benchmark FROM documents d LEFT JOIN (SELECT DISTINCT doc_id FROM labels) l ON d.doc_id = l.doc_id")
def join_semi_anti(spark, sf_dir):
    docs, labels, bench = t(spark, sf_dir, "documents"), t(spark, sf_dir, "labels"), t(spark, sf_dir, "benchmark").select("text")
    counts = [docs.join(labels, "doc_id", "left_semi").agg(F.count("*").alias("labelled")), docs.join(labels, "doc_id", "left_anti").agg(F.count("*").alias("unlabelled")), docs.join(bench, "text", "left_anti").agg(F.count("*").alias("not_benchmark"))]
    return counts[0].crossJoin(counts[1]).crossJoin(counts[2])


@query(f"SELECT tau, round(sum({pin_sql('s_acctbal - 5000', 'tau')}), 4) AS loss FROM supplier, (VALUES (0.5::double), (0.75)) AS g(tau) GROUP BY tau")
def join_cross_grid(spark, sf_dir):
    grid = spark.createDataFrame([(0.5,), (0.75,)], "tau double")
    return t(spark, sf_dir, "supplier").crossJoin(F.broadcast(grid)).groupBy("tau").agg(F.round(F.sum(L.pinball(F.col("s_acctbal") - 5000.0, F.col("tau"))), 4).alias("loss"))


@query("SELECT band, count(*) AS n FROM events JOIN (VALUES ('low', 0, 25), ('mid', 25, 100), ('high', 100, 100000)) AS b(band, lo, hi) ON value >= lo AND value < hi GROUP BY band")
def join_range_band(spark, sf_dir):
    bands = spark.createDataFrame([("low", 0.0, 25.0), ("mid", 25.0, 100.0), ("high", 100.0, 1e5)], "band string, lo double, hi double")
    return rel.range_join(t(spark, sf_dir, "events"), "value", bands, "lo", "hi").groupBy("band").agg(F.count("*").alias("n"))


@query("SELECT e.event_id, p.value AS last_purchase FROM (SELECT * FROM events WHERE event_type = 'error') e ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY ALL) p ON e.user_id = p.user_id AND e.ts >= p.ts")
def join_asof_purchase(spark, sf_dir):
    ev = t(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type", "value")
    bought = ev.where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return rel.asof_join(ev.where("event_type = 'error'"), bought, "user_id", "ts", "value", "last_purchase").select("event_id", "last_purchase")


@query("SELECT v.event_id AS view_id, c.event_id AS click_id FROM events v JOIN events c ON v.user_id = c.user_id AND c.ts >= v.ts AND c.ts <= v.ts + INTERVAL 1 HOUR WHERE v.event_type = 'view' AND c.event_type = 'click'")
def join_interval_hour(spark, sf_dir):
    ev = t(spark, sf_dir, "events")
    v = ev.where("event_type = 'view'").select("user_id", F.col("event_id").alias("view_id"), F.col("ts").alias("view_ts"))
    c = ev.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("ts").alias("click_ts"))
    return rel.interval_join(v, c, "user_id", "view_ts", "click_ts", 3600).select("view_id", "click_id")


RINV = [[1.0, -0.5], [0.0, 2.0]]


@query("SELECT s_suppkey::varchar AS row_id, round(abs(1.0::double) + abs(-0.5 + 2.0 * s_nationkey), 6) AS lam FROM supplier")
def join_coo_product(spark, sf_dir):
    import numpy as np

    coo = D.to_coo(D.supplier_design(spark, sf_dir))
    return sampling.row_norms_coo(coo, np.array(RINV)).select("row_id", F.round("lam", 6).alias("lam"))


@query(f"SELECT j, round(sum(b), 4) AS total, count(*) AS n FROM ({D.skew_sql(5, 2.0)}) GROUP BY j")
def join_salted(spark, sf_dir):
    rows = D.skew_lineitem(spark, sf_dir, 5, 2.0, engine="portable").select("row_id", "b", (F.array_position("x", F.lit(1.0)) - 1).cast("int").alias("j"))
    names = spark.createDataFrame([(k,) for k in range(5)], "j int")
    out = rel.salted_sum(rel.salted_join(rows, names, "j"), "j", F.col("b"))
    return out.select("j", F.round("total", 4).alias("total"), "n")


@query("SELECT c_custkey, (SELECT max(o_totalprice) FROM orders WHERE o_custkey = c_custkey) AS top, round(c_acctbal / (SELECT sum(abs(c_acctbal)) FROM customer), 9) AS share FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")
def subquery_scalar_total(spark, sf_dir):
    for n in ("orders", "customer"):
        t(spark, sf_dir, n).createOrReplaceTempView(f"tallquant_{n}")
    return spark.sql("""SELECT c_custkey, x.top, round(c_acctbal / (SELECT sum(abs(c_acctbal)) FROM tallquant_customer), 9) AS share
FROM tallquant_customer c LEFT JOIN LATERAL (SELECT max(o_totalprice) AS top FROM tallquant_orders o WHERE o.o_custkey = c.c_custkey) x
WHERE EXISTS (SELECT 1 FROM tallquant_orders o WHERE o.o_custkey = c.c_custkey AND o_orderstatus = 'F')""")


# --- aggregates and windows ------------------------------------------------------------------


@query("SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS qty, round(avg(l_extendedprice), 4) AS price, count(*) AS n FROM lineitem GROUP BY ALL")
def agg_basic(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.count("*").alias("n"))


@query("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return t(spark, sf_dir, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@query("SELECT event_type, " + ", ".join(f"quantile_disc(value, {p}) AS d{k}, round(quantile_cont(value, {p}), 6) AS c{k}" for k, p in enumerate((0.1, 0.5, 0.75, 0.9, 0.95))) + " FROM events GROUP BY 1")
def agg_quantiles(spark, sf_dir):
    cols = [e for k, p in enumerate((0.1, 0.5, 0.75, 0.9, 0.95)) for e in (F.expr(f"percentile_disc({p}) WITHIN GROUP (ORDER BY value)").alias(f"d{k}"), F.round(F.percentile("value", p), 6).alias(f"c{k}"))]
    return t(spark, sf_dir, "events").groupBy("event_type").agg(*cols)


@query("SELECT event_type, quantile_disc(value, 0.5) AS exact_median, true AS near_by_rank, true AS near_by_kll, true AS near_users FROM events GROUP BY 1")
def agg_quantiles_approx(spark, sf_dir):
    """Approximate medians (rank sketch, KLL sketch) within two per cent of rank, distinct users within five per cent."""
    ev = t(spark, sf_dir, "events")
    exact = [F.expr(f"percentile_disc({p}) WITHIN GROUP (ORDER BY value)") for p in (0.48, 0.5, 0.52)]
    kll = F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(value), 0.5D)")
    users = F.abs(F.approx_count_distinct("user_id", 0.01) / F.count_distinct("user_id") - 1)
    return ev.groupBy("event_type").agg(
        exact[1].alias("exact_median"), F.percentile_approx("value", 0.5, 1000).between(exact[0], exact[2]).alias("near_by_rank"),
        kll.between(exact[0], exact[2]).alias("near_by_kll"), (users < 0.05).alias("near_users"),
    )


@query("""WITH r AS (SELECT l_linestatus AS s, l_extendedprice AS v, sum(l_quantity) OVER (PARTITION BY l_linestatus ORDER BY l_extendedprice RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS run, sum(l_quantity) OVER (PARTITION BY l_linestatus) AS total FROM lineitem)
SELECT s AS l_linestatus, min(v) AS q FROM r WHERE run >= 0.5 * total GROUP BY s""")
def agg_weighted_quantile(spark, sf_dir):
    return quantreg.group_quantile_exact(t(spark, sf_dir, "lineitem"), "l_linestatus", "l_extendedprice", "l_quantity", 0.5)


@query("SELECT l_returnflag, round(regr_slope(l_extendedprice, l_quantity), 5) AS slope, round(corr(l_extendedprice, l_quantity), 7) AS r, round(covar_pop(l_extendedprice, l_quantity), 3) AS cov, round(stddev_samp(l_quantity), 6) AS sd FROM lineitem GROUP BY 1")
def agg_regression(spark, sf_dir):
    y, x = F.col("l_extendedprice"), F.col("l_quantity")
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.round(F.regr_slope(y, x), 5).alias("slope"), F.round(F.corr(y, x), 7).alias("r"), F.round(F.covar_pop(y, x), 3).alias("cov"), F.round(F.stddev_samp(x), 6).alias("sd"))


_G = "round(sum(l_quantity), 2) AS qty, grouping(l_returnflag)::int AS g1, grouping(l_linestatus)::int AS g2 FROM lineitem"


@query(f"SELECT l_returnflag, l_linestatus, {_G} GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube(spark, sf_dir):
    out = t(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus")
    return out.agg(F.round(F.sum("l_quantity"), 2).alias("qty"), F.grouping("l_returnflag").cast("int").alias("g1"), F.grouping("l_linestatus").cast("int").alias("g2"))


@query(f"SELECT l_returnflag, l_linestatus, {_G} GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def agg_rollup(spark, sf_dir):
    out = t(spark, sf_dir, "lineitem").rollup("l_returnflag", "l_linestatus")
    return out.agg(F.round(F.sum("l_quantity"), 2).alias("qty"), F.grouping("l_returnflag").cast("int").alias("g1"), F.grouping("l_linestatus").cast("int").alias("g2"))


@query(f"SELECT l_returnflag, l_linestatus, {_G} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def agg_grouping_sets(spark, sf_dir):
    t(spark, sf_dir, "lineitem").createOrReplaceTempView("tallquant_lineitem")
    return spark.sql("SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS qty, cast(grouping(l_returnflag) AS int) AS g1, cast(grouping(l_linestatus) AS int) AS g2 FROM tallquant_lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")


KINDS = ["click", "error", "purchase", "signup", "view"]


@query("SELECT day(ts) AS day, " + ", ".join(f"round(quantile_cont(value, 0.5) FILTER (event_type = '{k}'), 6) AS \"{k}\"" for k in KINDS) + " FROM events GROUP BY 1")
def agg_pivot(spark, sf_dir):
    out = t(spark, sf_dir, "events").groupBy(F.dayofmonth("ts").cast("long").alias("day")).pivot("event_type", KINDS).agg(F.percentile("value", 0.5))
    return out.select("day", *[F.round(k, 6).alias(k) for k in KINDS])


@query("SELECT day(ts) AS day, event_type, count(*) AS n FROM events GROUP BY ALL")
def agg_unpivot(spark, sf_dir):
    wide = t(spark, sf_dir, "events").groupBy(F.dayofmonth("ts").cast("long").alias("day")).pivot("event_type", KINDS).count()
    return wide.unpivot(["day"], KINDS, "event_type", "n").where("n IS NOT NULL")


@query("SELECT event_type, arg_min(event_id, value * 1000000 + event_id) AS least_id, count(*) FILTER (value > 100) AS large, bool_and(value >= 0) AS fine, len(list_distinct(list(user_id)))::int AS users FROM events GROUP BY 1")
def agg_best_of(spark, sf_dir):
    order = F.col("value") * 1_000_000 + F.col("event_id")
    return t(spark, sf_dir, "events").groupBy("event_type").agg(F.min_by("event_id", order).alias("least_id"), F.count(F.when(F.col("value") > 100, 1)).alias("large"), F.bool_and(F.col("value") >= 0).alias("fine"), F.size(F.collect_set("user_id")).alias("users"))


_CELLS = ["b", *[f"x[{j + 1}]" for j in range(11)]]


@query(" UNION ALL ".join(f"SELECT {i} AS i, {j} AS j, round(sum({_CELLS[i]} * {_CELLS[j]}), 2) AS v FROM c" for i in range(12) for j in range(i, 12)).join([f"WITH c AS MATERIALIZED ({D.census_sql()}) ", ""]))
def agg_gram(spark, sf_dir):
    from tallquant.operators.linalg import gram

    rows = D.census_design(spark, sf_dir).withColumn("a", F.concat(F.array("b"), "x"))
    g = gram(rows, "a")
    return spark.createDataFrame([(i, j, round(float(g[i, j]), 2)) for i in range(12) for j in range(i, 12)], "i int, j int, v double")


_W = "OVER (PARTITION BY event_type ORDER BY value, event_id)"


@query(f"SELECT event_id, row_number() {_W} AS rn, ntile(4) {_W} AS nt, round(percent_rank() {_W}, 6) AS pr, round(cume_dist() {_W}, 6) AS cd, rank() OVER (PARTITION BY event_type ORDER BY value) AS rk, dense_rank() OVER (PARTITION BY event_type ORDER BY value) AS dr FROM events")
def win_ranking(spark, sf_dir):
    w, v = Window.partitionBy("event_type").orderBy("value", "event_id"), Window.partitionBy("event_type").orderBy("value")
    return t(spark, sf_dir, "events").select("event_id", F.row_number().over(w).alias("rn"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"))


_U = "OVER (PARTITION BY user_id ORDER BY ts, event_id)"


@query(f"SELECT event_id, lag(value) {_U} AS before, lead(value, 2) {_U} AS ahead, first_value(value) {_U} AS fst, last_value(value) {_U} AS lst, nth_value(value, 2) {_U} AS second FROM events")
def win_analytic(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t(spark, sf_dir, "events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value", 2).over(w).alias("ahead"), F.first("value").over(w).alias("fst"), F.last("value").over(w).alias("lst"), F.nth_value("value", 2).over(w).alias("second"))


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS last3, round(sum(value) OVER (PARTITION BY user_id ORDER BY epoch(ts)::bigint RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW), 4) AS day FROM events")
def win_frames(spark, sf_dir):
    rows = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    secs = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-86_400, 0)
    # seconds are rounded to nearest, as the cast of the other engine does
    ev = t(spark, sf_dir, "events").withColumn("sec", F.round(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000).cast("long"))
    return ev.select("event_id", F.round(F.sum("value").over(rows), 4).alias("last3"), F.round(F.sum("value").over(secs), 4).alias("day"))


@query("SELECT event_id, round(abs(value) + 1, 6) AS lam FROM events ORDER BY abs(value) + 1 DESC, event_id LIMIT 10 OFFSET 5")
def topk_global(spark, sf_dir):
    ev = t(spark, sf_dir, "events").select("event_id", F.round(F.abs("value") + 1, 6).alias("lam"))
    return ev.orderBy(F.desc("lam"), "event_id").offset(5).limit(10)


@query("SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) WHERE k <= 3")
def topk_group(spark, sf_dir):
    return rel.top_per_group(t(spark, sf_dir, "orders"), "o_custkey", [F.desc("o_totalprice"), F.col("o_orderkey")], 3).select("o_custkey", "o_orderkey")


_S = "SELECT o_custkey FROM orders WHERE o_orderstatus = "


@query(" UNION ALL ".join(f"SELECT '{name}' AS op, count(*) AS n FROM ({_S}'F' {op} {_S}'O')" for name, op in (("union", "UNION"), ("union_all", "UNION ALL"), ("intersect", "INTERSECT"), ("except", "EXCEPT"), ("intersect_all", "INTERSECT ALL"), ("except_all", "EXCEPT ALL"))))
def set_ops(spark, sf_dir):
    orders = t(spark, sf_dir, "orders")
    f, o = (orders.where(F.col("o_orderstatus") == s).select("o_custkey") for s in "FO")
    ops = {"union": f.union(o).distinct(), "union_all": f.unionByName(o), "intersect": f.intersect(o), "except": f.subtract(o), "intersect_all": f.intersectAll(o), "except_all": f.exceptAll(o)}
    out = None
    for name, df in ops.items():
        part = df.agg(F.count("*").alias("n")).select(F.lit(name).alias("op"), "n")
        out = part if out is None else out.union(part)
    return out


# --- functions --------------------------------------------------------------------------------


@query("SELECT event_id, round(exp(-value / 100), 9) AS e, round(ln(1 + value), 9) AS l, round(sqrt(value), 9) AS s, round(pow(value, 1.5), 4) AS p, round(tan(value / 1000), 9) AS t, sign(value - 50)::double AS g, floor(value)::bigint AS f, ceil(value)::bigint AS c, ((event_id - 7) % 5 + 5) % 5 AS m, greatest(value, 50.0) AS hi, least(value, 50.0) AS lo FROM events")
def fn_math(spark, sf_dir):
    v = F.col("value")
    return t(spark, sf_dir, "events").select("event_id", F.round(F.exp(-v / 100), 9).alias("e"), F.round(F.log(1 + v), 9).alias("l"), F.round(F.sqrt(v), 9).alias("s"), F.round(F.pow(v, F.lit(1.5)), 4).alias("p"), F.round(F.tan(v / 1000), 9).alias("t"), F.signum(v - 50).alias("g"), F.floor(v).alias("f"), F.ceil(v).alias("c"), F.pmod(F.col("event_id") - 7, F.lit(5)).alias("m"), F.greatest(v, F.lit(50.0)).alias("hi"), F.least(v, F.lit(50.0)).alias("lo"))


@query("SELECT doc_id, length(text) AS n, lower(substr(text, 1, 8)) AS head, concat_ws('-', lang, source) AS tag, regexp_extract(source, '([0-9]+)', 1) AS num, regexp_replace(source, 'src', 's') AS short, trim('  ' || lang || ' ') AS tr, source LIKE 'src1%' AS one, md5(lang) AS h FROM documents")
def fn_string(spark, sf_dir):
    c = F.col
    return t(spark, sf_dir, "documents").select("doc_id", F.length("text").cast("long").alias("n"), F.lower(F.substring("text", 1, 8)).alias("head"), F.concat_ws("-", "lang", "source").alias("tag"), F.regexp_extract("source", "([0-9]+)", 1).alias("num"), F.regexp_replace("source", "src", "s").alias("short"), F.trim(F.concat(F.lit("  "), c("lang"), F.lit(" "))).alias("tr"), c("source").like("src1%").alias("one"), F.md5("lang").alias("h"))


@query("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_trunc('month', o_orderdate)::date AS mo, date_diff('day', DATE '1995-01-01', o_orderdate::date) AS d, (o_orderdate::date + 30) AS later FROM orders")
def fn_datetime(spark, sf_dir):
    day = F.to_date("o_orderdate")
    return t(spark, sf_dir, "orders").select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m"), F.to_date(F.date_trunc("month", "o_orderdate")).alias("mo"), F.datediff(day, F.lit("1995-01-01").cast("date")).cast("long").alias("d"), F.date_add(day, 30).alias("later"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding[1:4], lambda x: 2 * x::double)), 6) AS s, len(list_filter(embedding, lambda x: x > 0))::int AS pos, round(list_max(embedding)::double, 6) AS mx, round(list_min(embedding)::double, 6) AS mn, round(list_sort(embedding)[2]::double, 6) AS second FROM embeddings")
def fn_array(spark, sf_dir):
    e = F.col("embedding")
    two = F.aggregate(F.transform(F.slice(e, 1, 4), lambda x: 2 * x.cast("double")), F.lit(0.0), lambda a, x: a + x)
    return t(spark, sf_dir, "embeddings").select("vec_id", F.round(two, 6).alias("s"), F.size(F.filter(e, lambda x: x > 0)).alias("pos"), F.round(F.array_max(e).cast("double"), 6).alias("mx"), F.round(F.array_min(e).cast("double"), 6).alias("mn"), F.round(F.element_at(F.sort_array(e), 2).cast("double"), 6).alias("second"))


@query("SELECT event_id, (props->>'k')::int AS k FROM events")
def fn_map_json(spark, sf_dir):
    ev = t(spark, sf_dir, "events")
    a = F.from_json("props", "map<string,int>")["k"]
    b = F.get_json_object("props", "$.k").cast("int")
    c = F.try_variant_get(F.try_parse_json("props"), "$.k", "int")
    return ev.where(a.eqNullSafe(b) & a.eqNullSafe(c)).select("event_id", F.element_at(F.map_from_arrays(F.array(F.lit("k")), F.array(a)), "k").alias("k"))


@query(f"SELECT event_id, md5(event_id::varchar) AS h, round({rnd.unit_sql(7, chr(39) + 'coin' + chr(39), 'event_id')}, 12) AS u FROM events")
def fn_hash(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.md5(F.col("event_id").cast("string")).alias("h"), F.round(rnd.unit(7, "coin", F.col("event_id"), "portable"), 12).alias("u"))


@query("SELECT o_orderkey, o_totalprice::int AS i, o_orderkey::varchar AS s, try_cast(o_orderpriority AS int) AS bad FROM orders")
def fn_cast(spark, sf_dir):
    return t(spark, sf_dir, "orders").select("o_orderkey", F.rint("o_totalprice").cast("int").alias("i"), F.col("o_orderkey").cast("string").alias("s"), F.col("o_orderpriority").try_cast("int").alias("bad"))


# --- UDF surface ---------------------------------------------------------------------------------


@query("SELECT vec_id, round(embedding[1]::double + 2 * embedding[2]::double, 6) AS dot, round(list_sum(list_transform(embedding, lambda x: abs(x::double))), 5) AS l1 FROM embeddings")
def udf_scalar(spark, sf_dir):
    x = F.transform("embedding", lambda v: v.cast("double"))
    beta = F.array(*[F.lit(v) for v in [1.0, 2.0] + [0.0] * 62])
    emb = t(spark, sf_dir, "embeddings").select("vec_id", x.alias("x"), beta.alias("beta"))
    return emb.select("vec_id", F.round(udfs.dot_udf("x", "beta"), 6).alias("dot"), F.round(udfs.l1_norm_udf("x"), 5).alias("l1"))


@query("SELECT event_type, quantile_disc(value, 0.75) AS q FROM events GROUP BY 1")
def udf_grouped_agg(spark, sf_dir):
    return t(spark, sf_dir, "events").groupBy("event_type").agg(udfs.weighted_quantile_udf("value", F.lit(1.0), F.lit(0.75)).alias("q"))


@query("SELECT event_type AS grp, quantile_disc(value, 0.5) AS q FROM events GROUP BY 1")
def udf_grouped_map(spark, sf_dir):
    design = D.build(t(spark, sf_dir, "events"), F.col("event_id"), F.col("value"), [F.lit(1.0)], grp=F.col("event_type"))
    return quantreg.quantile_fit_by(design, [0.5]).select("grp", F.col("beta")[0].alias("q"))


@query("SELECT event_type AS grp, 0.75::double AS tau, quantile_disc(value, 0.75) AS beta, count(*) AS n_rows FROM events GROUP BY 1")
def udtf_fit(spark, sf_dir):
    D.ship(spark)
    udfs.register(spark)
    D.build(t(spark, sf_dir, "events"), F.col("event_id"), F.col("value"), [F.lit(1.0)], grp=F.col("event_type")).select("grp", "b", "x").createOrReplaceTempView("tallquant_rows")
    return spark.sql("SELECT grp, tau, beta, n_rows FROM quantile_fit(TABLE(tallquant_rows) PARTITION BY (grp), 0.75D)")


@query(f"SELECT event_type, round(sum({pin_sql('value - q', 0.75)}), 4) AS loss FROM events JOIN (SELECT event_type, quantile_disc(value, 0.75) AS q FROM events GROUP BY 1) USING (event_type) GROUP BY 1")
def udf_cogroup(spark, sf_dir):
    import pandas as pd

    ev = t(spark, sf_dir, "events").select("event_type", "value")
    fits = ev.groupBy("event_type").agg(F.expr("percentile_disc(0.75) WITHIN GROUP (ORDER BY value)").alias("q"))

    def score(rows: pd.DataFrame, fit: pd.DataFrame) -> pd.DataFrame:
        z = rows.value - fit.q.iloc[0]
        return pd.DataFrame({"event_type": [fit.event_type.iloc[0]], "loss": [float((0.75 * z).where(z >= 0, -0.25 * z).sum())]})

    out = ev.groupBy("event_type").cogroup(fits.groupBy("event_type")).applyInPandas(score, "event_type string, loss double")
    return out.select("event_type", F.round("loss", 4).alias("loss"))


@query(f"SELECT round(sum({pin_sql('value - 40', 0.75)}), 4) AS loss FROM events")
def udf_sql_function(spark, sf_dir):
    udfs.register(spark)
    t(spark, sf_dir, "events").createOrReplaceTempView("tallquant_events")
    return spark.sql("SELECT round(sum(pinball(value - 40, 0.75D)), 4) AS loss FROM tallquant_events")


# --- streams ----------------------------------------------------------------------------------------

FILES = 4
LATE = 50  # every such event arrives last, whatever its time


def _arriving(spark, sf_dir, late: bool = True) -> DataFrame:
    """Events in time order, four files of a trigger each, and late events in a fifth."""
    slot = streams.time_slot(spark, sf_dir, FILES)
    number = F.when(F.col("event_id") % LATE == 7, FILES).otherwise(slot) if late else slot
    return streams.events_stream(spark, sf_dir, 1, streams.events_in_files(spark, sf_dir, number, FILES + late))


@query(f"SELECT date_trunc('day', ts)::timestamp AS start, event_type, count(*) AS n, round(sum({pin_sql('value - 40', 0.75)}), 4) AS loss, quantile_disc(value, 0.75) AS q FROM events GROUP BY ALL")
def stream_windows(spark, sf_dir):
    out = streams.drain(streams.window_losses(_arriving(spark, sf_dir), 40.0, 0.75), "complete")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", "loss", "q")


@query("SELECT (to_timestamp(0)::timestamp + INTERVAL 6 HOUR * (floor(epoch(ts) / 21600)::bigint - k))::timestamp AS start, event_type, count(*) AS n FROM events, range(2) AS r(k) GROUP BY ALL".replace("to_timestamp(0)::timestamp", "TIMESTAMP '1970-01-01'"))
def stream_sliding(spark, sf_dir):
    out = streams.drain(streams.window_losses(_arriving(spark, sf_dir), 40.0, 0.75, "12 hours", "6 hours"), "complete")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query(f"""WITH g AS (SELECT *, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS k FROM g)
SELECT user_id, min(ts) AS start, count(*) AS n, round(sum({pin_sql('value - 40', 0.75)}), 4) AS loss FROM s GROUP BY user_id, k""")
def stream_sessions(spark, sf_dir):
    out = streams.drain(streams.session_losses(_arriving(spark, sf_dir, late=False), 40.0, 0.75), "complete")
    return out.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n", "loss")


LATE_SQL = f"""
WITH b AS (SELECT min(floor(epoch(ts))) AS lo, max(floor(epoch(ts))) AS hi FROM events), e AS (SELECT *, floor({FILES} * (floor(epoch(ts)) - lo) / (hi - lo + 1)) AS slot FROM events, b),
m AS (SELECT max(ts) AS seen FROM e WHERE event_id % {LATE} <> 7 AND slot < {FILES - 1})
SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM e, m WHERE event_id % {LATE} <> 7 OR ts > seen - INTERVAL 2 HOUR"""


@query(LATE_SQL)
def stream_late(spark, sf_dir):
    """Rows behind the watermark are dropped, the others stay once each; a batch is filtered by the watermark that the batch before it had."""
    out = streams.drain(streams.deduplicated(_arriving(spark, sf_dir)))
    return out.agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("ids"))


#: Rows of an arriving file beyond which it is written and read in pieces.
PIECE_ROWS = 1_000_000


@query("SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events")
def stream_repeated(spark, sf_dir):
    """Files that arrive twice: their rows count once."""
    pieces = 1 + t(spark, sf_dir, "events").count() // PIECE_ROWS
    path = streams.events_in_files(spark, sf_dir, streams.time_slot(spark, sf_dir, 2), 2, pieces)
    spark.read.parquet(path).coalesce(2 * pieces).write.mode("append").parquet(path)
    out = streams.drain(streams.deduplicated(streams.events_stream(spark, sf_dir, pieces, path), "100 days"))
    return out.agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("ids"))


@query(f"SELECT bucket, {significant_sql('v0')}, {significant_sql('v1')} FROM ({sketch_sql(CAUCHY_SQL)})")
def stream_sketch(spark, sf_dir):
    out = streams.drain(streams.sketch_stream(_arriving(spark, sf_dir), R, SEED), "complete")
    return out.select("bucket", *significant("v0"), *significant("v1"))


@query(f"SELECT event_type, event_id FROM (SELECT event_type, event_id, row_number() OVER (PARTITION BY event_type ORDER BY {rnd.unit_sql(SEED, chr(39) + 'coin0' + chr(39), 'event_id')} / (abs(value) + 1)) AS k FROM events) WHERE k <= 20")
def stream_sample(spark, sf_dir):
    out = streams.drain(streams.online_sample(_arriving(spark, sf_dir), 20, SEED), "update")
    return rel.top_per_group(out.dropDuplicates(["event_id"]), "event_type", [F.col("ratio")], 20).select("event_type", "event_id")


@query("SELECT v.event_id AS view_id, c.event_id AS click_id FROM events v JOIN events c ON v.user_id = c.user_id AND c.ts >= v.ts AND c.ts <= v.ts + INTERVAL 1 HOUR WHERE v.event_type = 'view' AND c.event_type = 'click'")
def stream_join(spark, sf_dir):
    return streams.drain(streams.views_then_clicks(_arriving(spark, sf_dir, late=False)))


@query("SELECT event_type, round(sum(value - q), 4) AS total FROM events JOIN (SELECT event_type, quantile_disc(value, 0.5) AS q FROM events GROUP BY 1) USING (event_type) GROUP BY 1")
def stream_static_join(spark, sf_dir):
    fits = t(spark, sf_dir, "events").groupBy("event_type").agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY value)").alias("q"))
    fits = spark.createDataFrame(fits.collect(), fits.schema)  # one row a type; else every batch would fit again
    out = streams.drain(streams.join_fits(_arriving(spark, sf_dir), fits))
    return out.groupBy("event_type").agg(F.round(F.sum("residual"), 4).alias("total"))


@query(" UNION ALL ".join(f"SELECT event_id % 3 AS batch, count(*) AS n, {p}::double AS tau, quantile_disc(value, {p}) AS q FROM events GROUP BY 1" for p in (0.5, 0.95)))
def stream_refit(spark, sf_dir):
    path = streams.events_in_files(spark, sf_dir, F.col("event_id") % 3, 3)
    rows = streams.refit_each_batch(streams.events_stream(spark, sf_dir, 1, path), [0.5, 0.95])
    return spark.createDataFrame(rows, "batch long, n long, tau double, q double")


@query("SELECT count(*) AS n, sum(((event_id % 100) + 100) % 100)::bigint AS total FROM events")
def stream_rate(spark, sf_dir):
    """One micro-batch of 100 numbered rows meets every event of its number."""
    events = t(spark, sf_dir, "events").select(F.pmod("event_id", F.lit(100)).cast("long").alias("value"), "ts")
    met = streams.rate_stream(spark, 100).select("value").join(events, "value")
    return streams.drain(met.groupBy().agg(F.count("ts").alias("n"), F.sum("value").cast("long").alias("total")), "complete")


@query(PAIRS_SQL.replace("SELECT round(min(f), 5) AS objective, round(arg_min(c0, f), 6) AS beta0, round(arg_min(c1, f), 6) AS beta1 FROM f", "SELECT round(arg_min(c0, f), 6) AS beta0 FROM f"))
def fit_saved_and_loaded(spark, sf_dir):
    fits = quantreg.exact_fit(D.supplier_design(spark, sf_dir), [0.75])
    path = storage.scratch(spark, "fit")
    storage.save_fits(fits, path)
    return storage.load_fits(spark, path).select(F.round(F.col("beta")[0], 6).alias("beta0"))


