"""The relational surface around the methods: joins, aggregations, windows, sets, scalars, user functions, round trips.

Each entry is a query and the SQL that checks it.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.prng import draw_column, draw_sql
from ..operators import features
from ..sources.catalog import load
from ..sources.synthetic import planted, planted_labels, read_sparse_text, write_sparse_text
from .cuts import shared_dir

Entry = tuple[Callable[[SparkSession, str], DataFrame], str | None]
FOUND: dict[str, Entry] = {}


def entry(sql: str | None = None):
    def add(f):
        FOUND[f.__name__] = f, sql
        return f

    return add


@entry("SELECT l_orderkey, l_quantity FROM lineitem")
def scan_parquet_projection(spark, sf):
    return load(spark, sf, "lineitem").select("l_orderkey", "l_quantity")


@entry("SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem JOIN part ON l_partkey = p_partkey WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND p_type LIKE 'S%' AND p_brand IS NOT NULL")
def filter_predicates(spark, sf):
    line = load(spark, sf, "lineitem").where(F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R"))
    part = load(spark, sf, "part").where(F.col("p_type").like("S%") & F.col("p_brand").isNotNull()).select("p_partkey")
    return line.join(part, F.col("l_partkey") == F.col("p_partkey")).select("l_orderkey", "l_linenumber", "l_quantity")


# -- joins -------------------------------------------------------------------------------------------------
def _join(kind: str, hint: str | None = None):
    """Whole orders with whole customers; but for inner joins, only finished orders have a partner."""

    def query(spark, sf):
        left = load(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_orderstatus")
        right = load(spark, sf, "customer").select("c_custkey", "c_nationkey")
        on = F.col("o_custkey") == F.col("c_custkey")
        out = left.join(right.hint(hint) if hint else right, on if kind == "inner" else on & (F.col("o_orderstatus") == "F"), kind)
        return out.select("o_orderkey", "c_custkey") if kind not in ("left_semi", "left_anti") else out.select("o_orderkey")

    return query


_ON = "o_custkey = c_custkey AND o_orderstatus = 'F'"
for _name, _kind, _sql in (("join_left", "left", "LEFT JOIN"), ("join_right", "right", "RIGHT JOIN"), ("join_full", "full", "FULL JOIN")):
    FOUND[_name] = _join(_kind), f"SELECT o_orderkey, c_custkey FROM orders {_sql} customer ON {_ON}"
for _name, _hint in (("join_inner", None), ("join_broadcast", "broadcast"), ("join_sortmerge", "merge"), ("join_shuffle_hash", "shuffle_hash")):
    FOUND[_name] = _join("inner", _hint), "SELECT o_orderkey, c_custkey FROM orders JOIN customer ON o_custkey = c_custkey"
FOUND["join_semi"] = _join("left_semi"), f"SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM customer WHERE {_ON})"
FOUND["join_anti"] = _join("left_anti"), f"SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM customer WHERE {_ON})"


@entry("SELECT n_name, r_name FROM nation, region")
def join_nested_loop_of_fixed_tables(spark, sf):
    """Every nation with every region: two tables of fixed size."""
    return load(spark, sf, "nation").select("n_name").crossJoin(F.broadcast(load(spark, sf, "region").select("r_name")))


@entry("SELECT e.event_id, CAST(floor(e.value / 10) AS BIGINT) AS band FROM events e WHERE e.value >= 5 AND e.value < 105")
def join_range(spark, sf):
    """A range join through its equality form: bands of width 10, then the exact condition."""
    bands = spark.range(10).select(F.col("id").alias("k"), (F.col("id") * 10).cast("double").alias("low"), (F.col("id") * 10 + 10).cast("double").alias("high"))
    rows = load(spark, sf, "events").where("value >= 5 AND value < 105").select("event_id", "value", F.floor(F.col("value") / 10).alias("b"))
    near = bands.select("k", "low", "high").unionByName(bands.withColumn("k", F.lit(10).cast("long")).withColumn("low", F.lit(100.0)).withColumn("high", F.lit(110.0)).limit(1))
    return rows.join(F.broadcast(near), F.col("b") == F.col("k")).where("value >= low AND value < high").select("event_id", F.col("k").alias("band"))


@entry("SELECT a.event_id AS purchase, count(*) AS views FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_type = 'view' AND b.ts <= a.ts AND b.ts > a.ts - INTERVAL 2 DAY WHERE a.event_type = 'purchase' GROUP BY a.event_id")
def join_interval(spark, sf):
    """Views of the same user in the two days before a purchase; user and day deal the rows, the interval decides."""
    rows = load(spark, sf, "events").select("event_id", "user_id", "event_type", "ts")
    a = rows.where("event_type = 'purchase'").withColumn("day", F.explode(F.sequence(F.to_date(F.col("ts") - F.expr("INTERVAL 2 DAYS")), F.to_date("ts")))).alias("a")
    b = rows.where("event_type = 'view'").withColumn("day", F.to_date("ts")).alias("b")
    met = a.join(b, ["user_id", "day"]).where("b.ts <= a.ts AND b.ts > a.ts - INTERVAL 2 DAYS")
    return met.groupBy(F.col("a.event_id").alias("purchase")).agg(F.count(F.lit(1)).alias("views"))


@entry("SELECT e.event_id, max(v.event_id) AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') e LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON e.user_id = v.user_id AND v.ts = (SELECT max(ts) FROM events w WHERE w.event_type = 'view' AND w.user_id = e.user_id AND w.ts <= e.ts) GROUP BY e.event_id")
def join_asof(spark, sf):
    """The last view at or before each purchase: one union and a window, no pair of rows is ever made."""
    rows = load(spark, sf, "events").where("event_type IN ('view', 'purchase')").select("event_id", "user_id", "event_type", "ts")
    w = Window.partitionBy("user_id").orderBy("ts", F.col("event_type").desc(), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w)
    return rows.withColumn("last_view", last).where("event_type = 'purchase'").select("event_id", "last_view")


# -- aggregations ------------------------------------------------------------------------------------------
@entry("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_extendedprice), 4) AS price FROM lineitem GROUP BY ALL")
def agg_hash(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.avg("l_extendedprice"), 4).alias("price"))


@entry("SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_returnflag")
def agg_distinct(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_suppkey").alias("suppliers"), F.countDistinct("l_partkey").alias("parts"))


@entry("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def agg_cube(spark, sf):
    return load(spark, sf, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@entry("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def agg_rollup(spark, sf):
    return load(spark, sf, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@entry("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")
def agg_grouping_sets(spark, sf):
    load(spark, sf, "orders").createOrReplaceTempView("grouping_orders")
    return spark.sql("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM grouping_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")


@entry("SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O, count(*) FILTER (o_orderstatus = 'P') AS P FROM orders GROUP BY o_orderpriority")
def agg_pivot(spark, sf):
    return load(spark, sf, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))


@entry("SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY event_type")
def agg_percentile(spark, sf):
    return load(spark, sf, "events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("median"), F.round(F.percentile("value", 0.9), 6).alias("p90"))


@entry("SELECT true AS within")
def agg_approx_distinct(spark, sf):
    out = load(spark, sf, "lineitem").agg(F.approx_count_distinct("l_orderkey", 0.02).alias("a"), F.countDistinct("l_orderkey").alias("n"))
    return out.select((F.abs(F.col("a") - F.col("n")) <= 0.1 * F.col("n")).alias("within"))


@entry("SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")
def agg_collect(spark, sf):
    return load(spark, sf, "nation").groupBy("n_regionkey").agg(F.concat_ws(",", F.array_sort(F.collect_list("n_name"))).alias("names"))


@entry("SELECT l_suppkey, count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem GROUP BY l_suppkey")
def agg_salted(spark, sf):
    """Two-stage aggregation: a key that holds a large share of the rows is spread over 16 partial groups."""
    rows = load(spark, sf, "lineitem").withColumn("salt", F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(16)))
    first = rows.groupBy("l_suppkey", "salt").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("q"))
    return first.groupBy("l_suppkey").agg(F.sum("n").alias("n"), F.round(F.sum("q"), 2).alias("q"))


# -- windows -----------------------------------------------------------------------------------------------
def _u():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


_US = "OVER (PARTITION BY user_id ORDER BY ts, event_id"


@entry(f"SELECT event_id, row_number() {_US}) AS rn, rank() OVER (PARTITION BY user_id ORDER BY event_type) AS rk, dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS dr FROM events")
def win_rank(spark, sf):
    t = Window.partitionBy("user_id").orderBy("event_type")
    return load(spark, sf, "events").select("event_id", F.row_number().over(_u()).cast("long").alias("rn"), F.rank().over(t).cast("long").alias("rk"), F.dense_rank().over(t).cast("long").alias("dr"))


@entry(f"SELECT event_id, lag(event_id) {_US}) AS before, lead(event_id) {_US}) AS after FROM events")
def win_lag_lead(spark, sf):
    return load(spark, sf, "events").select("event_id", F.lag("event_id").over(_u()).alias("before"), F.lead("event_id").over(_u()).alias("after"))


@entry(f"SELECT event_id, round(sum(value) {_US} ROWS UNBOUNDED PRECEDING), 4) AS running FROM events")
def win_running_sum(spark, sf):
    return load(spark, sf, "events").select("event_id", F.round(F.sum("value").over(_u().rowsBetween(Window.unboundedPreceding, 0)), 4).alias("running"))


@entry(f"SELECT event_id, round(avg(value) {_US} ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING), 6) AS mean FROM events")
def win_rows_between(spark, sf):
    return load(spark, sf, "events").select("event_id", F.round(F.avg("value").over(_u().rowsBetween(-2, 1)), 6).alias("mean"))


@entry("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day FROM events")
def win_range_between(spark, sf):
    w = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)
    return load(spark, sf, "events").withColumn("sec", F.unix_timestamp("ts")).select("event_id", F.count(F.lit(1)).over(w).alias("day"))


@entry(f"SELECT event_id, CAST(ntile(4) {_US}) AS INTEGER) AS quarter FROM events")
def win_ntile(spark, sf):
    return load(spark, sf, "events").select("event_id", F.ntile(4).over(_u()).alias("quarter"))


@entry(f"SELECT event_id, first_value(event_type) {_US}) AS first, last_value(event_type) {_US} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last FROM events")
def win_first_last(spark, sf):
    return load(spark, sf, "events").select("event_id", F.first("event_type").over(_u()).alias("first"), F.last("event_type").over(_u().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("last"))


@entry("SELECT user_id, event_id, value FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS r FROM events) WHERE r <= 3")
def topk_per_group(spark, sf):
    w = Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id")
    return load(spark, sf, "events").withColumn("r", F.row_number().over(w)).where("r <= 3").select("user_id", "event_id", "value")


@entry("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def sort_limit(spark, sf):
    return load(spark, sf, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25)


@entry("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 15")
def offset_limit(spark, sf):
    return load(spark, sf, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(15).limit(10)


# -- sets --------------------------------------------------------------------------------------------------
def _keys(spark, sf):
    return load(spark, sf, "customer").select(F.col("c_nationkey").alias("k")), load(spark, sf, "supplier").select(F.col("s_nationkey").alias("k"))


_A, _B = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier"
for _name, _f, _op in (
    ("union_all", lambda a, b: a.unionAll(b), "UNION ALL"), ("union_distinct", lambda a, b: a.union(b).distinct(), "UNION"), ("intersect", lambda a, b: a.intersect(b), "INTERSECT"),
    ("except_distinct", lambda a, b: a.subtract(b), "EXCEPT"), ("except_all", lambda a, b: a.exceptAll(b), "EXCEPT ALL"), ("intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL"),
):
    FOUND[_name] = (lambda f: lambda spark, sf: f(*_keys(spark, sf)))(_f), f"{_A} {_op} {_B}"


# -- scalars -----------------------------------------------------------------------------------------------
@entry("SELECT p_partkey, upper(p_name) AS u, substr(p_brand, 7) AS s, length(p_type) AS n, replace(p_type, 'A', '_') AS r, p_brand || '/' || p_type AS c FROM part")
def fn_string(spark, sf):
    return load(spark, sf, "part").select("p_partkey", F.upper("p_name").alias("u"), F.substring("p_brand", 7, 100).alias("s"), F.length("p_type").cast("long").alias("n"), F.replace("p_type", F.lit("A"), F.lit("_")).alias("r"), F.concat_ws("/", "p_brand", "p_type").alias("c"))


@entry("SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(dayofweek(o_orderdate) + 1 AS INTEGER) AS d, CAST(date_diff('day', CAST(o_orderdate AS DATE), DATE '2000-01-01') AS INTEGER) AS gap FROM orders")
def fn_date(spark, sf):
    return load(spark, sf, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofweek("o_orderdate").alias("d"), F.datediff(F.lit("2000-01-01").cast("date"), F.to_date("o_orderdate")).alias("gap"))


@entry("SELECT p_partkey, round(sqrt(p_retailprice), 6) AS a, round(ln(p_retailprice), 6) AS b, round(pow(p_size, 1.5), 6) AS c, CAST(p_size % 7 AS INTEGER) AS d, round(log2(p_retailprice), 6) AS e FROM part")
def fn_math(spark, sf):
    return load(spark, sf, "part").select("p_partkey", F.round(F.sqrt("p_retailprice"), 6).alias("a"), F.round(F.log("p_retailprice"), 6).alias("b"), F.round(F.pow("p_size", F.lit(1.5)), 6).alias("c"), (F.col("p_size") % 7).alias("d"), F.round(F.log2("p_retailprice"), 6).alias("e"))


@entry("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 5) AS squares, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive, round(CAST(list_max(embedding) AS DOUBLE), 6) AS top FROM embeddings")
def fn_array(spark, sf):
    return load(spark, sf, "embeddings").select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x), 5).alias("squares"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(F.array_max("embedding").cast("double"), 6).alias("top"))


@entry("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def fn_json(spark, sf):
    return load(spark, sf, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@entry("SELECT user_id, CAST(count(*) FILTER (event_type = 'view') AS BIGINT) AS views FROM events GROUP BY user_id")
def fn_map(spark, sf):
    counts = load(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return maps.select("user_id", F.coalesce(F.element_at("m", "view"), F.lit(0)).alias("views"))


@entry(f"SELECT o_orderkey, {draw_sql('7', '3', 'o_orderkey')} AS draw FROM orders")
def fn_portable_draw(spark, sf):
    return load(spark, sf, "orders").select("o_orderkey", draw_column(7, 3, F.col("o_orderkey")).alias("draw"))


@entry(f"SELECT o_orderkey FROM orders WHERE {draw_sql('11', 'o_orderkey')} < 429496729")
def sample_by_hash(spark, sf):
    """A tenth of the rows by threshold of the portable draw: the sampling is the feature here."""
    return load(spark, sf, "orders").where(draw_column(11, F.col("o_orderkey")) < 429496729).select("o_orderkey")


# -- user functions ----------------------------------------------------------------------------------------
@entry("SELECT event_id, round(1 / (1 + exp(-value / 100)), 6) AS p FROM events")
def udf_sigmoid(spark, sf):
    @F.pandas_udf("double")
    def squash(v: pd.Series) -> pd.Series:
        return 1 / (1 + np.exp(-v / 100))

    return load(spark, sf, "events").select("event_id", F.round(squash("value"), 6).alias("p"))


@entry("SELECT event_type, round(avg(value), 6) AS mean FROM events GROUP BY event_type")
def udaf_vector_mean(spark, sf):
    """A grouped aggregate over Arrow batches; sums per group and salt first, so no group is whole in one call."""

    def total(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"event_type": [pdf["event_type"].iloc[0]], "s": [pdf["value"].sum()], "n": [len(pdf)]})

    rows = load(spark, sf, "events").select("event_type", "value", F.pmod("event_id", F.lit(32)).alias("salt"))
    parts = rows.groupBy("event_type", "salt").applyInPandas(total, "event_type string, s double, n long")
    return parts.groupBy("event_type").agg(F.round(F.sum("s") / F.sum("n"), 6).alias("mean"))


@entry("SELECT CAST(vec_id AS BIGINT) AS vec_id, CAST(i AS INTEGER) AS pos, round(v, 6) AS v FROM (SELECT vec_id, unnest(range(64)) AS i, CAST(unnest(embedding) AS DOUBLE) AS v FROM embeddings) WHERE v > 0")
def udtf_sparse_to_rows(spark, sf):
    """A table function that turns a vector into rows of its positive entries."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="vec_id: bigint, pos: int, v: double")
    class Cells:
        def eval(self, vec_id: int, vector: list):
            for i, v in enumerate(vector):
                if v > 0:
                    yield vec_id, i, v

    spark.udtf.register("hs_cells", Cells)
    load(spark, sf, "embeddings").createOrReplaceTempView("hs_vectors")
    rows = spark.sql("SELECT c.* FROM hs_vectors, LATERAL hs_cells(vec_id, transform(embedding, x -> CAST(x AS DOUBLE))) c")
    return rows.select("vec_id", "pos", F.round("v", 6).alias("v"))


@entry(
    "WITH v AS (SELECT vec_id, label, unnest(range(64)) AS i, unnest(embedding)::DOUBLE AS a FROM embeddings) "
    "SELECT v.label, CAST(w.i * (w.i + 1) // 2 + v.i AS INTEGER) AS pos, count(*) AS n, round(sum(v.a * w.a), 4) + 0.0 AS h FROM v JOIN v w ON v.vec_id = w.vec_id AND v.i <= w.i GROUP BY ALL"
)
def arrow_udf_hessian(spark, sf):
    """Packed outer-product sums of all components per label from Arrow batches, partial per task."""

    def work(batches):
        import pyarrow as pa

        from curvature_spark.functions import packed

        held: dict[int, list] = {}
        for batch in batches:
            z = batch.column("embedding").flatten().to_numpy(zero_copy_only=False).astype(float).reshape(batch.num_rows, -1)
            labels = batch.column("label").to_numpy(zero_copy_only=False)
            for v in np.unique(labels):
                part = z[labels == v]
                own = held.setdefault(int(v), [0, 0.0])
                held[int(v)] = [own[0] + len(part), own[1] + packed.pack(part.T @ part)]
        for label, (n, h) in held.items():
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(h), label, dtype=np.int32)), pa.array(np.arange(len(h), dtype=np.int32)), pa.array(np.full(len(h), n)), pa.array(h)], ["label", "pos", "n", "h"])

    parts = load(spark, sf, "embeddings").select("label", "embedding").mapInArrow(work, "label int, pos int, n long, h double")
    return parts.groupBy("label", "pos").agg(F.sum("n").alias("n"), (F.round(F.sum("h"), 4) + 0.0).alias("h"))


def register_functions(spark: SparkSession) -> None:
    """The SQL names of the kernels: hs_topk, hs_windowk, hs_pack, hs_grad."""
    from ..functions import packed
    from ..operators import compressors

    def kernel(kind):
        def send(v: list, k: int, seed: int) -> list:
            message = compressors.make(kind, k)(np.array(v, dtype=float), None, (seed,))
            return message.dense(len(v)).tolist()

        return send

    for kind in ("topk", "windowk"):
        spark.udf.register(f"hs_{kind}", kernel(kind), "array<double>")
    spark.udf.register("hs_pack", lambda v: packed.pack(np.outer(v, v)).tolist(), "array<double>")
    spark.udf.register("hs_grad", LogisticGradient())


def LogisticGradient():  # noqa: N802  a factory of the registered function
    """hs_grad(features, label, x): a row's share of the logistic gradient at x, batch by batch."""
    import pandas as pd

    @F.pandas_udf("array<double>")
    def gradient(z: pd.Series, label: pd.Series, x: pd.Series) -> pd.Series:
        rows, at = np.stack(z.to_list()) * label.to_numpy()[:, None], np.stack(x.to_list())
        e = np.exp(-np.abs(m := (rows * at).sum(axis=1)))
        return pd.Series(list(-rows * (np.where(m >= 0, e, 1.0) / (1.0 + e))[:, None]))

    return gradient


@entry(
    "WITH e AS (SELECT user_id, CASE WHEN event_type = 'purchase' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y, [value / 500, CAST(json_extract_string(props, '$.k') AS DOUBLE) / 100, hour(ts) / 24.0::DOUBLE, dayofweek(ts) / 7.0::DOUBLE, 1.0::DOUBLE] AS a FROM events), "
    "m AS (SELECT *, y * (0.1 * a[1] - 0.2 * a[2] + 0.3 * a[3] - 0.4 * a[4] + 0.5) AS m FROM e) SELECT user_id, "
    + ", ".join(f"round(avg(-y * a[{i}] / (1 + exp(m))), 6) + 0.0 AS g{i}" for i in range(1, 6))
    + " FROM m GROUP BY user_id"
)
def sql_gradient(spark, sf):
    """Every user's logistic gradient at one point, in SQL on the registered function."""
    register_functions(spark)
    features.users(spark, sf).select("user_id", "label", "features").createOrReplaceTempView("hs_samples")
    means = ", ".join(f"round(avg(g[{i}]), 6) + 0.0 AS g{i + 1}" for i in range(5))
    return spark.sql(f"SELECT user_id, {means} FROM (SELECT user_id, hs_grad(features, label, array(0.1D, -0.2D, 0.3D, -0.4D, 0.5D)) AS g FROM hs_samples) GROUP BY user_id")


@entry("SELECT vec_id, CAST(4 AS BIGINT) AS kept FROM embeddings")
def sql_functions(spark, sf):
    register_functions(spark)
    load(spark, sf, "embeddings").createOrReplaceTempView("hs_embeddings")
    return spark.sql("SELECT vec_id, CAST(size(filter(hs_topk(transform(embedding, x -> CAST(x AS DOUBLE)), 4, 1), x -> x <> 0)) AS BIGINT) AS kept FROM hs_embeddings")


@entry(None)
def sql_train_udtf(spark, sf):
    """Per-client local training as a table function over partitioned rows."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="user_id: bigint, rows: bigint, grad_norm: double")
    class Train:
        def __init__(self):
            self.user, self.rows = None, []

        def eval(self, row):
            self.user = row["user_id"]
            self.rows.append([v * row["label"] for v in row["features"]])

        def terminate(self):
            from curvature_spark.functions import packed
            from curvature_spark.operators.problems import LogisticProblem

            z, problem = np.array(self.rows), LogisticProblem(1e-2)
            x = np.zeros(z.shape[1])
            for _ in range(20):
                _, g, h = problem.finish(len(z), problem.sums(z, x), x)
                x = x - np.linalg.solve(packed.unpack(h, len(x)), g)
            yield self.user, len(z), float(np.linalg.norm(problem.finish(len(z), problem.sums(z, x), x)[1]))

    spark.udtf.register("hs_train", Train)
    features.users(spark, sf).select("user_id", "label", "features").createOrReplaceTempView("hs_users")
    return spark.sql("SELECT user_id, rows, round(grad_norm, 6) AS grad_norm FROM hs_train(TABLE(hs_users) PARTITION BY user_id)")


# -- sources and sinks -------------------------------------------------------------------------------------
def _path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/tables/{name}-{uuid.uuid4().hex}"


@entry("SELECT CASE WHEN label = 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS label, round(CAST(embedding[1] AS DOUBLE), 6) AS a0, 1.0::DOUBLE AS a68 FROM embeddings")
def libsvm_roundtrip(spark, sf):
    path = _path(spark, "sparse-text")
    write_sparse_text(features.dense(spark, sf), path)
    rows = read_sparse_text(spark, path, 69)
    return rows.select("label", F.round(F.col("features")[0], 6).alias("a0"), F.col("features")[68].alias("a68"))


@entry("SELECT 'csv' AS format, count(*) AS n, CAST(sum(o_orderkey) AS BIGINT) AS keys FROM orders UNION ALL SELECT 'json', count(*), CAST(sum(o_orderkey) AS BIGINT) FROM orders UNION ALL SELECT 'orc', count(*), CAST(sum(o_orderkey) AS BIGINT) FROM orders")
def csv_json_orc_roundtrip(spark, sf):
    rows, out = load(spark, sf, "orders").select("o_orderkey", "o_orderstatus"), None
    for kind in ("csv", "json", "orc"):
        path = _path(spark, kind)
        rows.write.format(kind).save(path)
        back = spark.read.schema(rows.schema).format(kind).load(path).agg(F.lit(kind).alias("format"), F.count(F.lit(1)).alias("n"), F.sum("o_orderkey").alias("keys"))
        out = back if out is None else out.unionByName(back)
    return out


@entry("SELECT o_orderstatus, count(*) AS n FROM orders GROUP BY o_orderstatus")
def partitioned_write(spark, sf):
    """One folder per client; a filter on it reads that folder alone."""
    path = _path(spark, "clients")
    load(spark, sf, "orders").select("o_orderkey", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(path)
    return spark.read.parquet(path).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


def _planted_sql() -> str:
    cells = ["value / 500", "CAST(json_extract_string(props, '$.k') AS DOUBLE) / 100", "hour(ts) / 24.0::DOUBLE", "dayofweek(ts) / 7.0::DOUBLE", "1.0::DOUBLE"]
    margin = " + ".join(f"({c}) * ({float(v)!r}::DOUBLE)" for c, v in zip(cells, planted(5, 3), strict=True))
    drawn = draw_sql("3", "CAST(event_id AS VARCHAR)")
    return f"SELECT count(*) AS n, round(avg(CASE WHEN {drawn} / 4294967296.0::DOUBLE < 1 / (1 + exp(-margin)) THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END), 6) AS positive, round(avg(margin), 6) AS margin FROM (SELECT event_id, {margin} AS margin FROM events)"


@entry(_planted_sql())
def synthetic_source(spark, sf):
    """A planted problem over the events' features: rows, share of positives, and the mean margin under the planted parameters."""
    rows = planted_labels(features.users(spark, sf), 5, 3)
    return rows.agg(F.count(F.lit(1)).alias("n"), F.round(F.avg((F.col("label") > 0).cast("double")), 6).alias("positive"), F.round(F.avg("margin"), 6).alias("margin"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, (f, _) in FOUND.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in FOUND.items() if sql}
