"""Design rows: ``row_id string, b double, x array<double>, w double``.

Layouts: *dense* (one array), *sparse* (struct of indices and values), *coo* (one
row for each entry) and *wide* (one column for each covariate).
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tallquant.functions import randomness as rnd
from tallquant.session import ship

LINE_ID = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def line_id() -> Column:
    """The six columns that identify a line item."""
    return F.concat_ws("|", *[F.col(c).cast("string") for c in LINE_ID])


def line_id_sql(prefix: str = "") -> str:
    return "concat_ws('|', " + ", ".join(f"({prefix}{c})::varchar" for c in LINE_ID) + ")"


def build(df: DataFrame, row_id: Column, b: Column, x: list[Column], w: Column | None = None, on_bad: str = "drop", grp: Column | None = None) -> DataFrame:
    """Design rows from expressions; rows with a null, NaN or infinite value are dropped, or fail the job."""
    cells = F.array(*[c.cast("double") for c in x])
    rows = df.select(row_id.cast("string").alias("row_id"), b.cast("double").alias("b"), cells.alias("x"), (w.cast("double") if w is not None else F.lit(1.0)).alias("w"), *([grp.cast("string").alias("grp")] if grp is not None else []))
    fine = F.col("b").isNotNull() & ~F.isnan("b") & (F.abs("b") < float("inf")) & F.forall("x", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    if on_bad == "fail":
        return rows.where(F.when(fine, F.lit(True)).otherwise(F.raise_error("design row with a null or non-finite value").cast("boolean")))
    return rows.where(fine)


def count_rejected(df: DataFrame, b: Column, x: list[Column]) -> DataFrame:
    bad = [c.cast("double").isNull() | F.isnan(c.cast("double")) | (F.abs(c.cast("double")) == float("inf")) for c in [b, *x]]
    any_bad = bad[0]
    for c in bad[1:]:
        any_bad = any_bad | c
    return df.agg(F.count("*").alias("rows"), F.count(F.when(any_bad, 1)).alias("rejected"))


def one_hot(value: Column, levels: list, base=None) -> list[Column]:
    """0/1 indicators of the levels, without the base level if one is named."""
    return [F.when(value == lvl, 1.0).otherwise(0.0) for lvl in levels if lvl != base]


def standardise(design: DataFrame) -> tuple[DataFrame, list[float], list[float]]:
    """Centre and scale columns by two-pass mean and deviation; constant columns stay."""
    d = len(design.select("x").first().x)
    row = design.agg(*[F.avg(F.col("x")[j]).alias(f"m{j}") for j in range(d)], *[F.coalesce(F.stddev_pop(F.col("x")[j]), F.lit(0.0)).alias(f"s{j}") for j in range(d)]).first()
    mean = [row[f"m{j}"] if row[f"s{j}"] > 0 else 0.0 for j in range(d)]
    scale = [row[f"s{j}"] or 1.0 for j in range(d)]
    return design.withColumn("x", F.array(*[(F.col("x")[j] - mean[j]) / scale[j] for j in range(d)])), mean, scale


def unscale(beta: list[float], mean: list[float], scale: list[float], intercept: int = 0) -> list[float]:
    """Coefficients of the original columns from those of standardised ones."""
    out = [v / s for v, s in zip(beta, scale, strict=True)]
    out[intercept] -= sum(v * m for v, m in zip(out, mean, strict=True))
    return out


def to_coo(design: DataFrame) -> DataFrame:
    return design.select("row_id", F.posexplode("x").alias("j", "v")).where("v <> 0")


def coo_to_dense(coo: DataFrame, d: int) -> DataFrame:
    cells = F.map_from_entries(F.collect_list(F.struct("j", "v")))
    return coo.groupBy("row_id").agg(cells.alias("m")).select("row_id", F.array(*[F.coalesce(F.try_element_at("m", F.lit(j)), F.lit(0.0)) for j in range(d)]).alias("x"))


def to_sparse(design: DataFrame) -> DataFrame:
    pairs = F.filter(F.transform("x", lambda v, j: F.struct(j.alias("j"), v.alias("v"))), lambda e: e["v"] != 0)
    return design.withColumn("x", F.struct(pairs["j"].alias("idx"), pairs["v"].alias("val")))


def sparse_to_dense(design: DataFrame, d: int) -> DataFrame:
    cells = F.map_from_arrays("x.idx", "x.val")
    return design.withColumn("x", F.array(*[F.coalesce(F.try_element_at(cells, F.lit(j)), F.lit(0.0)) for j in range(d)]))


def to_wide(design: DataFrame, d: int) -> DataFrame:
    return design.select("row_id", "b", "w", *[F.col("x")[j].alias(f"x{j}") for j in range(d)])


def nnz(design: DataFrame) -> DataFrame:
    """Entries that are not zero: the work of an input-sparsity pass."""
    return design.agg(F.sum(F.size(F.filter("x", lambda v: v != 0))).cast("long").alias("nnz"), F.count("*").alias("n_rows"))


def stack(design: DataFrame, copies: int) -> DataFrame:
    """The design repeated: the same optimum, ``copies`` times the loss."""
    return design.crossJoin(F.broadcast(design.sparkSession.range(copies).withColumnRenamed("id", "copy"))).withColumn("row_id", F.concat_ws("#", "row_id", "copy")).drop("copy")


def collapse(design: DataFrame) -> DataFrame:
    """Equal rows as one row whose weight is their sum."""
    return design.groupBy("b", "x").agg(F.sum("w").alias("w"), F.min("row_id").alias("row_id")).select("row_id", "b", "x", "w")


def prefix(design: DataFrame, share: float, seed: int = 11, engine: str = "fast") -> DataFrame:
    """A deterministic nested share of the rows."""
    return design.where(rnd.unit(seed, "prefix", F.col("row_id"), engine) < share)


# --- workloads -----------------------------------------------------------------


def skew_truth(d: int, seed: int) -> list[float]:
    """Gaussian coefficient of each column, by the portable generator."""
    import hashlib

    def u(stream: str, j: int) -> float:
        return (int(hashlib.md5(f"{seed}|{stream}|{j}".encode()).hexdigest()[:13], 16) + 0.5) / rnd.TWO52

    return [math.sqrt(-2 * math.log(u("truth_a", j))) * math.cos(2 * math.pi * u("truth_b", j)) for j in range(d)]


def skew_noise_scale(d: int, q: float, truth: list[float], ratio: float = 0.2) -> float:
    """Laplace scale at which noise over signal has the given l2 ratio."""
    share = [q**j * (q - 1) / (q**d - 1) for j in range(d)]
    return ratio * math.sqrt(sum(s * t * t for s, t in zip(share, truth, strict=True)) / 2)


def skew_design(rows: DataFrame, row_id: Column, d: int, q: float, seed: int = 3, engine: str = "fast") -> DataFrame:
    """One-hot rows in geometrically growing blocks, Laplace noise, and one response in a thousand replaced by 500 times the noise."""
    truth = skew_truth(d, seed)
    scale = skew_noise_scale(d, q, truth)
    ids = rows.select(row_id.alias("row_id"))
    u = lambda stream: rnd.unit(seed, stream, F.col("row_id"), engine)
    j = F.least(F.lit(d - 1), F.floor(F.log(1.0 + u("column") * (q**d - 1)) / math.log(q))).cast("int")
    placed = ids.select("row_id", j.alias("j"), (F.lit(scale) * rnd.laplace(u("noise"))).alias("e"), u("outlier").alias("o"))
    signal = F.array(*[F.lit(t) for t in truth])[F.col("j")]
    b = F.when(F.col("o") < 0.001, 500.0 * F.col("e")).otherwise(signal + F.col("e"))
    x = F.array(*[F.when(F.col("j") == k, 1.0).otherwise(0.0) for k in range(d)])  # a lambda would work the column out again for each cell
    return placed.select("row_id", b.alias("b"), x.alias("x"), F.lit(1.0).alias("w"))


def skew_sql(d: int, q: float, seed: int = 3, source: str = "lineitem", row_id: str | None = None) -> str:
    """DuckDB text of the portable skew design: row_id, j, b."""
    truth = skew_truth(d, seed)
    scale = skew_noise_scale(d, q, truth)
    row_id = row_id or line_id_sql()
    u = lambda s: rnd.unit_sql(seed, f"'{s}'", "row_id")
    values = "([" + ", ".join(repr(t) for t in truth) + "]::double[])"
    return f"""SELECT row_id, j, CASE WHEN o < 0.001 THEN 500.0 * e ELSE {values}[j + 1] + e END AS b FROM (
SELECT row_id, least({d - 1}, floor(ln(1.0::double + {u("column")}::double * {q**d - 1!r}::double) / {math.log(q)!r}::double))::int AS j,
  {scale!r}::double * (-sign({u("noise")}::double - 0.5) * ln(1.0::double - 2.0 * abs({u("noise")}::double - 0.5))) AS e, {u("outlier")}::double AS o
FROM (SELECT {row_id} AS row_id FROM {source}))"""


def skew_lineitem(spark: SparkSession, sf_dir: str, d: int = 10, q: float = 1.75, seed: int = 3, engine: str = "fast") -> DataFrame:
    return skew_design(table(spark, sf_dir, "lineitem"), line_id(), d, q, seed, engine)


def gaussian_design(spark: SparkSession, sf_dir: str, d: int = 11, copies: int = 1, seed: int = 5, engine: str = "fast") -> DataFrame:
    """Embedding components with hashed Gaussian jitter; response as in the skew design."""
    truth = skew_truth(d, seed)
    scale = 0.2 * math.sqrt(sum(t * t for t in truth) / 2)
    base = table(spark, sf_dir, "embeddings").crossJoin(F.broadcast(spark.range(copies).withColumnRenamed("id", "copy")))
    rows = base.select(F.concat_ws("#", "vec_id", "copy").alias("row_id"), "embedding")
    u = lambda s: rnd.unit(seed, s, F.col("row_id"), engine)
    x = F.array(*[8.0 * F.col("embedding")[j].cast("double") + 0.1 * rnd.gaussian(u(f"ga{j}"), u(f"gb{j}")) for j in range(d)])
    e = F.lit(scale) * rnd.laplace(u("noise"))
    rows = rows.select("row_id", x.alias("x"), e.alias("e"), u("outlier").alias("o"))
    signal = F.aggregate(F.zip_with("x", F.array(*[F.lit(t) for t in truth]), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    return rows.select("row_id", F.when(F.col("o") < 0.001, 500.0 * F.col("e")).otherwise(signal + F.col("e")).alias("b"), "x", F.lit(1.0).alias("w"))


def gaussian_sql(d: int, copies: int, seed: int = 5) -> str:
    """DuckDB text of the portable Gaussian design: row_id, b, x."""
    truth = skew_truth(d, seed)
    scale = 0.2 * math.sqrt(sum(t * t for t in truth) / 2)
    u = lambda s: rnd.unit_sql(seed, f"'{s}'", "row_id")
    normal = lambda j: f"sqrt(-2.0 * ln({u(f'ga{j}')})) * cos({2 * math.pi!r} * {u(f'gb{j}')})"
    cells = ", ".join(f"8.0 * embedding[{j + 1}]::double + 0.1 * {normal(j)}" for j in range(d))
    signal = " + ".join(f"x[{j + 1}] * {t!r}::double" for j, t in enumerate(truth))
    return f"""SELECT row_id, x, CASE WHEN o < 0.001 THEN 500.0 * e ELSE {signal} + e END AS b FROM (
SELECT row_id, [{cells}] AS x, {scale!r}::double * (-sign({u("noise")} - 0.5) * ln(1.0::double - 2.0 * abs({u("noise")} - 0.5))) AS e, {u("outlier")} AS o
FROM (SELECT vec_id || '#' || copy AS row_id, embedding FROM embeddings, range({copies}) AS c(copy)))"""


CENSUS_NAMES = ["intercept", "status_o", "y1996", "y1997", "y1998", "y1999", "y2000", "flag_r", "order_f", "e", "e2"]


def census_design(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Log price on intercept, indicators, ship-year bands, and a squared ordinal term (11 covariates)."""
    line = table(spark, sf_dir, "lineitem").select(line_id().alias("row_id"), "l_orderkey", "l_extendedprice", "l_linestatus", "l_returnflag", "l_shipdate", "l_quantity")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus")
    rows = line.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    year, e = F.year("l_shipdate"), F.floor(F.col("l_quantity") / 3).cast("double")
    flag = lambda c: F.when(c, 1.0).otherwise(0.0)
    x = [F.lit(1.0), flag(F.col("l_linestatus") == "O"), *[flag(year == y) for y in range(1996, 2000)], flag(year >= 2000), flag(F.col("l_returnflag") == "R"), flag(F.col("o_orderstatus") == "F"), e, e * e]
    return build(rows, F.col("row_id"), F.log("l_extendedprice"), x)


def census_sql() -> str:
    flag = lambda c: f"CASE WHEN {c} THEN 1.0::double ELSE 0.0::double END"
    e = "floor(l_quantity / 3)::double"
    cells = ["1.0::double", flag("l_linestatus = 'O'"), *[flag(f"year(l_shipdate) = {y}") for y in range(1996, 2000)], flag("year(l_shipdate) >= 2000"), flag("l_returnflag = 'R'"), flag("o_orderstatus = 'F'"), e, f"{e} * {e}"]
    return f"SELECT {line_id_sql()} AS row_id, ln(l_extendedprice) AS b, [{', '.join(cells)}] AS x FROM lineitem JOIN orders ON l_orderkey = o_orderkey"


CENSUS_TRUTH = [9.0, -0.3, 0.05, 0.1, 0.15, 0.2, 0.25, -0.1, 0.1, -0.02, 0.006]


def census_planted(spark: SparkSession, sf_dir: str, seed: int = 9, engine: str = "fast") -> DataFrame:
    """The census design with a planted response: at level tau, intercept and status slope shift by the noise quantile and half of it."""
    rows = census_design(spark, sf_dir)
    noise = 0.3 * rnd.laplace(rnd.unit(seed, "noise", F.col("row_id"), engine))
    signal = F.aggregate(F.zip_with("x", F.array(*[F.lit(v) for v in CENSUS_TRUTH]), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    return rows.withColumn("b", signal + (1.0 + 0.5 * F.col("x")[1]) * noise)


def planted_slopes(tau: float) -> list[float]:
    """Coefficients of the planted census response at level tau."""
    q = 0.3 * (math.log(2 * tau) if tau < 0.5 else -math.log(2 * (1 - tau)))
    out = list(CENSUS_TRUTH)
    out[0] += q
    out[1] += 0.5 * q
    return out


def onehot_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    ev = table(spark, sf_dir, "events")
    return build(ev, F.col("event_id"), F.col("value"), one_hot(F.col("event_type"), ["click", "error", "purchase", "signup", "view"]), grp=F.col("event_type"))


def onehot_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders")
    levels = [r.o_orderpriority for r in orders.select("o_orderpriority").distinct().orderBy("o_orderpriority").collect()]
    return build(orders, F.col("o_orderkey"), F.col("o_totalprice"), one_hot(F.col("o_orderpriority"), levels), grp=F.col("o_orderpriority"))


def supplier_design(spark: SparkSession, sf_dir: str) -> DataFrame:
    return build(table(spark, sf_dir, "supplier"), F.col("s_suppkey"), F.col("s_acctbal"), [F.lit(1.0), F.col("s_nationkey")])


def document_design(spark: SparkSession, sf_dir: str, d: int = 16) -> DataFrame:
    """Document length on hashed token counts, dense layout; token buckets by the portable hash."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "n_chars", F.explode(F.array_distinct(F.split(F.lower("text"), r"\s+"))).alias("token"))
    slot = F.pmod(F.conv(F.substring(F.md5("token"), 1, 8), 16, 10).cast("long"), F.lit(d)).cast("int")
    counts = docs.withColumn("j", slot).groupBy("doc_id", "n_chars").pivot("j", list(range(d))).count()
    return build(counts, F.col("doc_id"), F.col("n_chars"), [F.coalesce(F.col(str(j)), F.lit(0)) for j in range(d)])


def conversation_design(spark: SparkSession, sf_dir: str) -> DataFrame:
    conv = table(spark, sf_dir, "conversations")
    return build(conv, F.concat_ws("-", "conv_id", "turn"), F.length("text"), one_hot(F.col("role"), ["assistant", "system", "user"]), grp=F.col("role"))


def label_design(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id")
    return build(rows, F.col("doc_id"), F.col("n_chars"), [F.lit(1.0), F.col("quality"), F.col("toxic")])


def page_design(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    tags = lambda t: F.regexp_count("html", F.lit(f"<{t}[ >]"))
    return build(pages, F.col("page_id"), F.octet_length("html"), [F.lit(1.0), tags("p"), tags("a"), tags("div")])
