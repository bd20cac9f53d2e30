"""The relational operators around the methods, as thin functions over DataFrames, and
their registered queries with SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import checkpoint_folder, plan_bytes
from ..sources import graphs

BROADCAST_BYTES = 64 << 20


def join(left: DataFrame, right: DataFrame, on, how: str = "inner", strategy: str | None = None) -> DataFrame:
    """strategy: broadcast (size is checked), merge, shuffle_hash or None (Catalyst and AQE)."""
    if strategy == "broadcast":
        right = F.broadcast(right) if plan_bytes(right) <= BROADCAST_BYTES else right
    elif strategy:
        right = right.hint(strategy)
    return left.join(right, on, how)


def top_k(df: DataFrame, by: list, k: int) -> DataFrame:
    return df.orderBy(*by).limit(k)


def top_k_per_group(df: DataFrame, group: list[str], by: list, k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(*group).orderBy(*by))).where(F.col("rank") <= k)


def asof(left: DataFrame, right: DataFrame, by: str, at: str, value: str, name: str) -> DataFrame:
    """left with the latest value of right at or before each row's time: one shuffle and
    one window over the union, no range join."""
    a = left.withColumns({"_side": F.lit(1), "_v": F.lit(None).cast(dict(right.dtypes)[value])})
    b = right.select(by, at, F.col(value).alias("_v"), F.lit(0).alias("_side"))
    both = a.unionByName(b, allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(at, "_side", "_v").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn(name, F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_side", "_v")


def interval_pairs(df: DataFrame, at: str, node: str, seconds: int) -> DataFrame:
    """Pairs of different nodes with times at most `seconds` apart: a row goes to its own
    bucket and, on one side, to the neighbours; the residual condition decides."""
    t = F.unix_micros(F.col(at).cast("timestamp"))
    x = df.select(F.col(node).alias("a"), t.alias("ta")).withColumn("bucket", F.floor(F.col("ta") / (seconds * 1_000_000)).cast("long"))
    y = x.select(F.col("a").alias("b"), F.col("ta").alias("tb"), F.explode(F.array(F.col("bucket") - 1, F.col("bucket"), F.col("bucket") + 1)).alias("bucket"))
    return x.join(y, "bucket").where((F.col("a") < F.col("b")) & (F.abs(F.col("ta") - F.col("tb")) <= seconds * 1_000_000)).select("a", "b")


def set_op(a: DataFrame, b: DataFrame, kind: str) -> DataFrame:
    return {
        "union": lambda: a.union(b).distinct(), "union_all": lambda: a.union(b), "intersect": lambda: a.intersect(b), "intersect_all": lambda: a.intersectAll(b),
        "except": lambda: a.subtract(b), "except_all": lambda: a.exceptAll(b),
    }[kind]()


def round_trip(df: DataFrame, fmt: str, **options) -> str:
    """Write df once in a format to the shared folder; its path."""
    path = f"{checkpoint_folder(df.sparkSession)}/roundtrip-{fmt}-{uuid.uuid4().hex}"
    df.write.format(fmt).options(**options).save(path)
    return path


def _edges_back(fmt: str):
    def query(spark, sf_dir):
        e = graphs.copart_r(spark, sf_dir)
        if fmt == "text":
            return graphs.read_edge_list(spark, round_trip(e.select(F.concat_ws(" ", "src", "dst").alias("value")), "text"), "text")
        return graphs.read_edge_list(spark, round_trip(e, fmt), fmt)

    return query


def _adjacency_back(spark, sf_dir):
    from ..graph import PropertyGraph

    near = PropertyGraph(graphs.copart_r(spark, sf_dir)).adjacency()
    line = F.concat_ws(" ", F.col("id").cast("string"), F.concat_ws(" ", F.transform("nbrs", lambda x: x.cast("string"))))
    return graphs.read_adjacency_text(spark, round_trip(near.select(line.alias("value")), "text"))


def _sink_levels(spark, sf_dir):
    from .levels import scratch, write

    e = graphs.copart_r(spark, sf_dir)
    path = write(e.withColumn("block_id", F.pmod("src", F.lit(4)).cast("int")), scratch(e, "levels"), 2)
    return spark.read.parquet(path).groupBy("block_id").agg(F.count("*").alias("n"))


def queries() -> dict:
    """name -> (query, SQL or None)."""
    out: dict = {}
    T = graphs.table

    def add(name, fn, sql=None):
        out[name] = (fn, sql)

    def of(table, fn, *columns):
        return lambda s, d: fn(T(s, d, table, list(columns) or None))

    cr, c2 = graphs.SQL["copart_r"], graphs.SQL["copart_2"]
    for name in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "pages", "benchmark", "conversations"):
        add(f"op_scan_{name}", of(name, lambda df: df.agg(F.count("*").alias("n"))), f"SELECT count(*) AS n FROM {name}")
    add("op_scan_parquet", lambda s, d: T(s, d, "orders", ["o_orderkey", "o_totalprice"]), "SELECT o_orderkey, o_totalprice FROM orders")
    add("op_scan_edges", lambda s, d: graphs.edges_from_pairs(T(s, d, "lineitem", ["l_partkey", "l_suppkey"]), "l_partkey", "l_suppkey"), "SELECT DISTINCT least(l_partkey, l_suppkey) AS src, greatest(l_partkey, l_suppkey) AS dst FROM lineitem WHERE l_partkey <> l_suppkey")
    for fmt in ("csv", "json", "orc", "parquet", "text"):
        add(f"op_scan_{fmt}_edges", _edges_back(fmt), cr)
    add("op_adjlist_parse", _adjacency_back, cr)
    add("op_sink_levels", _sink_levels, f"SELECT (src % 4)::INT AS block_id, count(*) AS n FROM ({cr}) GROUP BY 1")
    add("op_project_cols", of("lineitem", lambda df: df.select("l_orderkey", "l_quantity"), "l_orderkey", "l_quantity"), "SELECT l_orderkey, l_quantity FROM lineitem")
    add("op_project_expr", of("lineitem", lambda df: df.select("l_orderkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("net"))), "SELECT l_orderkey, l_extendedprice * (1 - l_discount) AS net FROM lineitem")
    for name, cond in {
        "cmp": "o_totalprice > 50000", "between": "o_totalprice BETWEEN 10000 AND 20000", "in": "o_orderstatus IN ('F', 'O')", "like": "o_orderpriority LIKE '1%'",
        "null": "o_orderdate IS NOT NULL", "bool": "NOT (o_orderstatus = 'F' OR o_totalprice < 1000)",
    }.items():
        add(f"op_filter_{name}", of("orders", lambda df, c=cond: df.where(c).select("o_orderkey")), f"SELECT o_orderkey FROM orders WHERE {cond}")
    add("op_filter_rlike", of("part", lambda df: df.where(F.col("p_name").rlike("[aeiou]{2}")).select("p_partkey")), "SELECT p_partkey FROM part WHERE regexp_matches(p_name, '[aeiou]{2}')")
    add("op_case", of("lineitem", lambda df: df.groupBy(F.when(F.col("l_quantity") < 10, "low").when(F.col("l_quantity") < 30, "mid").otherwise("high").alias("band")).agg(F.count("*").alias("n"))),
        "SELECT CASE WHEN l_quantity < 10 THEN 'low' WHEN l_quantity < 30 THEN 'mid' ELSE 'high' END AS band, count(*) AS n FROM lineitem GROUP BY 1")

    def cn(strategy):
        return lambda s, d: join(T(s, d, "customer", ["c_custkey", "c_nationkey"]), T(s, d, "nation", ["n_nationkey", "n_name"]), F.col("c_nationkey") == F.col("n_nationkey"), "inner", strategy).select("c_custkey", "n_name")

    def ol(strategy):
        return lambda s, d: join(T(s, d, "lineitem", ["l_orderkey", "l_quantity"]), T(s, d, "orders", ["o_orderkey", "o_orderstatus"]), F.col("l_orderkey") == F.col("o_orderkey"), "inner", strategy).groupBy("o_orderstatus").agg(F.sum("l_quantity").alias("q"))

    add("op_join_inner_broadcast", cn("broadcast"), "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
    for strategy, key in (("merge", "sortmerge"), ("shuffle_hash", "hash")):
        add(f"op_join_inner_{key}", ol(strategy), "SELECT o_orderstatus, sum(l_quantity) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
    for how in ("left", "right", "full"):
        add(f"op_join_{how}", lambda s, d, how=how: T(s, d, "customer", ["c_custkey"]).join(T(s, d, "orders", ["o_orderkey", "o_custkey"]), F.col("c_custkey") == F.col("o_custkey"), how).select("c_custkey", "o_orderkey"),
            f"SELECT c_custkey, o_orderkey FROM customer {how.upper()} JOIN orders ON c_custkey = o_custkey")
    for how, word in (("left_semi", "EXISTS"), ("left_anti", "NOT EXISTS")):
        add(f"op_join_{how[5:]}", lambda s, d, how=how: T(s, d, "customer", ["c_custkey"]).join(T(s, d, "orders", ["o_custkey"]), F.col("c_custkey") == F.col("o_custkey"), how), f"SELECT c_custkey FROM customer WHERE {word} (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
    add("op_join_theta", lambda s, d: (lambda e: e.select("src", F.col("dst").alias("a")).join(e.select("src", F.col("dst").alias("b")), "src").where("a < b").groupBy("src").agg(F.count("*").alias("n")))(graphs.copart_r(s, d)),
        f"WITH e AS ({cr}) SELECT x.src, count(*) AS n FROM e x JOIN e y ON x.src = y.src AND x.dst < y.dst GROUP BY 1")
    add("op_join_nested", lambda s, d: T(s, d, "nation", ["n_nationkey"]).join(F.broadcast(T(s, d, "region", ["r_regionkey"])), F.col("n_nationkey") > F.col("r_regionkey") * 5), "SELECT n_nationkey, r_regionkey FROM nation JOIN region ON n_nationkey > r_regionkey * 5")
    add("op_join_range", lambda s, d: T(s, d, "part", ["p_partkey", "p_size"]).withColumn("band", F.expr("p_size div 10")).join(s.range(0, 6).selectExpr("id AS band", "id * 10 AS lo", "id * 10 + 5 AS hi"), "band").where("p_size BETWEEN lo AND hi").select("p_partkey", "lo"),
        "SELECT p_partkey, (p_size // 10 * 10)::BIGINT AS lo FROM part WHERE p_size % 10 <= 5 AND p_size < 60")
    add("op_join_interval", lambda s, d: interval_pairs(T(s, d, "events", ["ts", "user_id"]).where("event_type = 'purchase'"), "ts", "user_id", 30).groupBy("a", "b").agg(F.count("*").alias("n")),
        "SELECT x.user_id AS a, y.user_id AS b, count(*) AS n FROM events x JOIN events y ON x.user_id < y.user_id AND abs(epoch_us(x.ts) - epoch_us(y.ts)) <= 30000000 WHERE x.event_type = 'purchase' AND y.event_type = 'purchase' GROUP BY 1, 2")

    def clicks(s, d):
        ev = T(s, d, "events", ["event_id", "ts", "user_id", "event_type", "value"])
        right = ev.where("event_type = 'click'").groupBy("user_id", "ts").agg(F.max("value").alias("clicked"))
        return asof(ev.where("event_type = 'purchase'").select("event_id", "ts", "user_id"), right, "user_id", "ts", "clicked", "last_click").select("event_id", "last_click")

    add("op_join_asof", clicks, "SELECT p.event_id, c.value AS last_click FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN "
        "(SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'click' GROUP BY 1, 2) c ON p.user_id = c.user_id AND p.ts >= c.ts")
    add("op_join_cross", lambda s, d: T(s, d, "region", ["r_name"]).crossJoin(T(s, d, "region").select(F.col("r_name").alias("other"))), "SELECT a.r_name, b.r_name AS other FROM region a, region b")
    add("op_join_self", lambda s, d: T(s, d, "nation", ["n_name", "n_regionkey"]).alias("a").join(T(s, d, "nation", ["n_name", "n_regionkey"]).alias("b"), F.expr("a.n_regionkey = b.n_regionkey AND a.n_name < b.n_name")).select(F.col("a.n_name").alias("x"), F.col("b.n_name").alias("y")),
        "SELECT a.n_name AS x, b.n_name AS y FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_name < b.n_name")

    li = "lineitem"
    add("op_agg_hash", of(li, lambda df: df.groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("q"), F.count("*").alias("n"))), "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q, count(*) AS n FROM lineitem GROUP BY 1, 2")
    add("op_agg_sort", of("part", lambda df: df.groupBy("p_brand").agg(F.max("p_name").alias("last"))), "SELECT p_brand, max(p_name) AS last FROM part GROUP BY 1")
    add("op_agg_object", of(li, lambda df: df.groupBy("l_orderkey").agg(F.concat_ws(",", F.sort_array(F.collect_set("l_returnflag"))).alias("flags"))), "SELECT l_orderkey, string_agg(DISTINCT l_returnflag, ',' ORDER BY l_returnflag) AS flags FROM lineitem GROUP BY 1")
    add("op_agg_distinct", of(li, lambda df: df.groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"))), "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
    add("op_agg_multi_distinct", of(li, lambda df: df.groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))), "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
    add("op_agg_approx", of("events", lambda df: df.agg(F.approx_count_distinct("user_id", 0.02).alias("users"))))
    add("op_agg_bitmap", of(li, lambda df: df.groupBy(F.bitmap_bucket_number("l_partkey").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("l_partkey")).alias("m")).agg(F.sum(F.bitmap_count("m")).alias("parts"))), "SELECT count(DISTINCT l_partkey) AS parts FROM lineitem")
    for kind, sql in (("cube", "CUBE (l_returnflag, l_linestatus)"), ("rollup", "ROLLUP (l_returnflag, l_linestatus)")):
        add(f"op_agg_{kind}", of(li, lambda df, kind=kind: getattr(df, kind)("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))), f"SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY {sql}")
    add("op_agg_gsets", of(li, lambda df: df.groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))), "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")
    add("op_agg_pivot", of("orders", lambda df: df.groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O"]).agg(F.count(F.lit(1)))), "SELECT o_orderpriority, nullif(count(*) FILTER (o_orderstatus = 'F'), 0) AS F, nullif(count(*) FILTER (o_orderstatus = 'O'), 0) AS O FROM orders GROUP BY 1")
    add("op_agg_stats", of(li, lambda df: df.groupBy("l_returnflag").agg(F.round(F.avg("l_quantity"), 6).alias("mean"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.percentile("l_quantity", 0.5).alias("median"))),
        "SELECT l_returnflag, round(avg(l_quantity), 6) AS mean, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r, quantile_cont(l_quantity, 0.5) AS median FROM lineitem GROUP BY 1")
    add("op_agg_filter", of("orders", lambda df: df.agg(F.count_if(F.col("o_orderstatus") == "F").alias("f"), F.sum(F.when(F.col("o_totalprice") > 1000, 1)).alias("big"))), "SELECT count(*) FILTER (o_orderstatus = 'F') AS f, sum(CASE WHEN o_totalprice > 1000 THEN 1 END)::BIGINT AS big FROM orders")
    add("op_agg_having", of("orders", lambda df: df.groupBy("o_custkey").agg(F.count("*").alias("n")).where("n > 10")), "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 10")

    def w():
        return Window.partitionBy("o_custkey").orderBy("o_orderkey")

    wsql = "(PARTITION BY o_custkey ORDER BY o_orderkey)"
    ranks = {"row_number": F.row_number, "rank": F.rank, "dense_rank": F.dense_rank, "percent_rank": F.percent_rank, "ntile": lambda: F.ntile(4), "cume_dist": F.cume_dist}
    for name, fn in ranks.items():
        call = "ntile(4)" if name == "ntile" else f"{name}()"
        cast = "" if name in ("percent_rank", "cume_dist") else "::INT"
        add(f"op_win_{name}", of("orders", lambda df, fn=fn: df.select("o_orderkey", fn().over(w()).alias("r"))), f"SELECT o_orderkey, ({call} OVER {wsql}){cast} AS r FROM orders")
    more = {
        "lag": (lambda: F.lag("o_totalprice"), "lag(o_totalprice)"), "lead": (lambda: F.lead("o_totalprice"), "lead(o_totalprice)"), "first": (lambda: F.first("o_totalprice"), "first_value(o_totalprice)"),
        "last": (lambda: F.last("o_totalprice"), "last_value(o_totalprice)"), "nth": (lambda: F.nth_value("o_totalprice", 2), "nth_value(o_totalprice, 2)"),
    }
    for name, (fn, call) in more.items():
        add(f"op_win_{name}", of("orders", lambda df, fn=fn: df.select("o_orderkey", fn().over(w()).alias("r"))), f"SELECT o_orderkey, {call} OVER {wsql} AS r FROM orders")
    add("op_win_rows", of("orders", lambda df: df.select("o_orderkey", F.count("*").over(w().rowsBetween(-2, 0)).alias("n"), F.max("o_totalprice").over(w().rowsBetween(-2, 0)).alias("top"))), "SELECT o_orderkey, count(*) OVER z AS n, max(o_totalprice) OVER z AS top FROM orders WINDOW z AS (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)")
    add("op_win_range", of("orders", lambda df: df.select("o_orderkey", F.count("*").over(w().rangeBetween(-1000, 0)).alias("n"))), "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 1000 PRECEDING AND CURRENT ROW) AS n FROM orders")
    from ..plans import planning

    add("op_prefix_sum", lambda s, d: planning.prefix_sum(T(s, d, "orders", ["o_orderkey", "o_custkey"]), ["o_orderkey"], "o_custkey"), "SELECT o_orderkey, o_custkey, coalesce(sum(o_custkey) OVER (ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start_offset FROM orders")
    add("op_sort", of("orders", lambda df: df.select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey")), "SELECT o_orderkey, o_totalprice FROM orders")
    add("op_limit", of("orders", lambda df: top_k(df.select("o_orderkey"), ["o_orderkey"], 10)), "SELECT o_orderkey FROM orders ORDER BY 1 LIMIT 10")
    add("op_topk_tri_vertices", lambda s, d: top_k(_per_vertex(s, d), [F.desc("triangles"), "id"], 10),
        f"WITH e AS ({cr}), t AS (SELECT x.src AS a, x.dst AS b, y.dst AS c FROM e x JOIN e y ON y.src = x.src AND y.dst > x.dst JOIN e z ON z.src = x.dst AND z.dst = y.dst) SELECT v AS id, count(*) AS triangles FROM (SELECT a AS v FROM t UNION ALL SELECT b FROM t UNION ALL SELECT c FROM t) GROUP BY v ORDER BY 2 DESC, 1 LIMIT 10")
    add("op_topk_per_group", of("orders", lambda df: top_k_per_group(df.select("o_custkey", "o_orderkey", "o_totalprice"), ["o_custkey"], [F.desc("o_totalprice"), "o_orderkey"], 2)),
        "SELECT * FROM (SELECT o_custkey, o_orderkey, o_totalprice, (row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey))::INT AS rank FROM orders) WHERE rank <= 2")
    for kind in ("union", "union_all", "intersect", "intersect_all", "except", "except_all"):
        add(f"op_set_{kind}", lambda s, d, kind=kind: set_op(graphs.copart_r(s, d), graphs.copart_2(s, d), kind), f"SELECT src, dst FROM ({cr}) {kind.replace('_', ' ').upper()} SELECT src, dst FROM ({c2})")

    add("op_scalar_string", of("part", lambda df: df.select("p_partkey", F.upper("p_name").alias("u"), F.substring("p_name", 2, 3).alias("s"), F.char_length("p_name").alias("l"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("pad"), F.instr("p_name", "a").alias("at"), F.replace("p_brand", F.lit("#"), F.lit("-")).alias("b"))),
        "SELECT p_partkey, upper(p_name) AS u, substr(p_name, 2, 3) AS s, length(p_name)::INT AS l, lpad(p_size::VARCHAR, 4, '0') AS pad, instr(p_name, 'a')::INT AS at, replace(p_brand, '#', '-') AS b FROM part")
    add("op_scalar_date", of("orders", lambda df: df.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.datediff(F.col("o_orderdate"), F.lit("1990-01-01").cast("date")).alias("days"))),
        "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, date_diff('day', DATE '1990-01-01', o_orderdate::DATE)::INT AS days FROM orders")
    add("op_scalar_math", of("part", lambda df: df.select("p_partkey", F.abs(F.col("p_size") - 25).alias("a"), F.bit_count("p_partkey").cast("int").alias("b"), F.pmod("p_partkey", F.lit(7)).alias("c"), F.col("p_partkey").bitwiseXOR(F.lit(5)).alias("x"), F.shiftleft("p_partkey", 2).alias("sh"))),
        "SELECT p_partkey, abs(p_size - 25) AS a, bit_count(p_partkey)::INT AS b, p_partkey % 7 AS c, xor(p_partkey, 5) AS x, p_partkey << 2 AS sh FROM part")
    add("op_scalar_hash", of("part", lambda df: df.select("p_partkey", F.md5(F.col("p_name")).alias("m"), F.sha2("p_name", 256).alias("s"))), "SELECT p_partkey, md5(p_name) AS m, sha256(p_name) AS s FROM part")
    add("op_scalar_xxhash", of("part", lambda df: df.select("p_partkey", F.xxhash64("p_name").alias("h"))))
    add("op_scalar_array", of("embeddings", lambda df: df.select("vec_id", F.size("embedding").alias("n"), F.size(F.filter("embedding", lambda v: v > 0)).alias("pos"), F.exists("embedding", lambda v: v > 0.5).alias("any"), F.aggregate(F.transform("embedding", lambda v: F.floor(v.cast("double") * 100).cast("long")), F.lit(0).cast("long"), lambda a, v: a + v).alias("total"))),
        "SELECT vec_id, len(embedding)::INT AS n, len(list_filter(embedding, lambda v: v > 0))::INT AS pos, len(list_filter(embedding, lambda v: v > 0.5)) > 0 AS any, list_sum(list_transform(embedding, lambda v: floor(v::DOUBLE * 100)::BIGINT))::BIGINT AS total FROM embeddings")
    add("op_scalar_struct", of("nation", lambda df: df.groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_name", "n_nationkey"))).alias("m")).select("n_regionkey", F.size(F.map_keys("m")).alias("n"))), "SELECT n_regionkey, count(*)::INT AS n FROM nation GROUP BY 1")
    add("op_scalar_json", of("events", lambda df: df.select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "k long")["k"].alias("j"))), "SELECT event_id, (props::JSON->>'$.k')::BIGINT AS k, (props::JSON->>'$.k')::BIGINT AS j FROM events")
    add("op_scalar_html", of("pages", lambda df: df.select("page_id", F.size(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("links"))), "SELECT page_id, len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))::INT AS links FROM pages")
    add("op_scalar_null", of("customer", lambda df: df.select("c_custkey", F.coalesce(F.nullif("c_mktsegment", F.lit("BUILDING")), F.lit("none")).alias("s"), F.greatest("c_nationkey", F.lit(10)).alias("g"))), "SELECT c_custkey, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS s, greatest(c_nationkey, 10) AS g FROM customer")
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0).cast("long"), lambda t, v: t + v)
    add("op_scalar_vector", lambda s, d: (lambda v: v.alias("x").join(v.alias("y"), F.expr("y.vec_id = x.vec_id + 1")).select(F.col("x.vec_id").alias("vec_id"), F.round(dot(F.col("x.q"), F.col("y.q")) / F.sqrt(dot(F.col("x.q"), F.col("x.q")).cast("double") * dot(F.col("y.q"), F.col("y.q")).cast("double")), 9).alias("cosine")))(_quantised(T(s, d, "embeddings", ["vec_id", "embedding"]))),
        "WITH v AS (SELECT vec_id, list_transform(embedding, lambda e: floor(e::DOUBLE * 1000)) AS q FROM embeddings) SELECT x.vec_id, round(list_dot_product(x.q, y.q) / sqrt(list_dot_product(x.q, x.q) * list_dot_product(y.q, y.q)), 9) AS cosine FROM v x JOIN v y ON y.vec_id = x.vec_id + 1")
    add("op_scalar_text", of("documents", lambda df: df.select("doc_id", F.size(F.split("text", "\n")).alias("lines"), F.char_length("text").alias("chars"))), "SELECT doc_id, len(string_split(text, chr(10)))::INT AS lines, length(text)::INT AS chars FROM documents")
    add("op_udf_canon", _udf_canon)
    return out


def _quantised(df):
    return df.select("vec_id", F.transform("embedding", lambda e: F.floor(e.cast("double") * 1000).cast("long")).alias("q"))


def _per_vertex(spark, sf_dir):
    from ..apps import triangles

    return triangles.per_vertex(graphs.load(spark, sf_dir, "copart_r"))


def _udf_canon(spark, sf_dir):
    """Canonical code of labelled quick patterns by the generic search, on distinct ones."""
    from ..apps import frequent
    from . import engine
    from .rules import AppSpec

    g = graphs.load(spark, sf_dir, "comin")
    level = engine.mine(g, AppSpec(mode="edge"), 2).levels[2]
    return frequent.domains_generic(level).groupBy("pattern", "orbit").agg(F.count_distinct("vid").alias("n"))
