"""Graphs derived from ordinary tables, with the same rule as DuckDB SQL beside each.

Every function gives a DataFrame of canonical edges; SQL[name] is a query text with the
columns src and dst for checking.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import PropertyGraph, label_dictionary, normalise
from ..session import keep, ship

PART_OFFSET = 100_000_000


def table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def edges_from_pairs(df: DataFrame, a: str, b: str) -> DataFrame:
    return normalise(df, a, b)


def _pairs_on(df: DataFrame, key: str, node: str) -> DataFrame:
    """Pairs a < b of distinct nodes that share a key."""
    d = df.select(F.col(key).alias("k"), F.col(node).cast("long").alias("n")).where("n is not null").distinct()
    return d.alias("x").join(d.alias("y"), F.expr("x.k = y.k and x.n < y.n")).select(F.col("x.n").alias("src"), F.col("y.n").alias("dst"), F.col("x.k").alias("k"))


def copart_r(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_returnflag"]).where("l_returnflag = 'R'")
    return _pairs_on(lines, "l_orderkey", "l_partkey").select("src", "dst").distinct()


def copart_full(spark, sf_dir):
    return _pairs_on(table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"]), "l_orderkey", "l_partkey").select("src", "dst").distinct()


def copart_lists(spark, sf_dir):
    """id, nbrs: the neighbour lists of copart_full, without its edges as rows."""
    lines = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"])
    return _lists_on(lines, "l_orderkey", "l_partkey")


def _lists_on(df: DataFrame, key: str, node: str) -> DataFrame:
    """Neighbour lists, in order, of nodes that share a key; the members of a key are shuffled once
    for each of them, as a list."""
    d = df.select(F.col(key).alias("k"), F.col(node).cast("long").alias("n")).where("k is not null and n is not null")
    members = d.groupBy("k").agg(F.collect_set("n").alias("own")).where(F.size("own") > 1)
    beside = members.select(F.explode("own").alias("id"), "own").select("id", F.array_remove("own", F.col("id")).alias("own"))
    return beside.groupBy("id").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("own")))).alias("nbrs"))


def copart_2(spark, sf_dir):
    pairs = _pairs_on(table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"]), "l_orderkey", "l_partkey")
    return pairs.groupBy("src", "dst").agg(F.count("*").alias("n")).where("n >= 2").select("src", "dst")


def nextline(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_linenumber"])
    other = li.select(F.col("l_orderkey"), (F.col("l_linenumber") - 1).alias("l_linenumber"), F.col("l_partkey").alias("other"))
    return normalise(li.join(other, ["l_orderkey", "l_linenumber"]), "l_partkey", "other")


def supp_coorder(spark, sf_dir):
    return _pairs_on(table(spark, sf_dir, "lineitem", ["l_orderkey", "l_suppkey"]), "l_orderkey", "l_suppkey").select("src", "dst").distinct()


def comin(spark, sf_dir):
    return _pairs_on(comin_rows(spark, sf_dir), "k", "n").select("src", "dst").distinct()


def comin_rows(spark, sf_dir):
    """k, n: minutes and their users; users of a minute are joined in comin."""
    return table(spark, sf_dir, "events", ["ts", "user_id"]).select(F.date_trunc("minute", "ts").alias("k"), F.col("user_id").cast("long").alias("n"))


def custpart_top(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_returnflag", "l_quantity"]).where("l_returnflag = 'R' and l_quantity >= 40")
    orders = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"])
    both = li.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return both.select(F.col("o_custkey").cast("long").alias("src"), (F.col("l_partkey") + PART_OFFSET).cast("long").alias("dst")).distinct()


def tree(spark, sf_dir):
    nation = table(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"])
    customer = table(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"])
    up = nation.select((F.col("n_regionkey") + 1000).cast("long").alias("src"), (F.col("n_nationkey") + 2000).cast("long").alias("dst"))
    down = customer.select((F.col("c_nationkey") + 2000).cast("long").alias("src"), (F.col("c_custkey") + 10000).cast("long").alias("dst"))
    return up.unionByName(down).distinct()


def _vectors(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Ids, and a row of doubles each, of a table of ids and lists of one length."""
    ids = table.column(0).to_numpy()
    flat = table.column(1).combine_chunks().flatten().to_numpy().astype(np.float64)
    return ids, flat.reshape(len(ids), -1) if len(ids) else flat.reshape(0, 0)


def _nearest(sim: np.ndarray, k: int) -> np.ndarray:
    """Places of the k greatest values of each row, of equal ones the first; in no order."""
    if sim.shape[1] <= k:
        return np.broadcast_to(np.arange(sim.shape[1]), sim.shape)
    best = np.argpartition(sim, -k, axis=1)[:, -k:]
    least = np.take_along_axis(sim, best, 1).min(1)
    for i in np.flatnonzero((sim >= least[:, None]).sum(1) > k):
        above = np.flatnonzero(sim[i] > least[i])
        best[i] = np.append(above, np.flatnonzero(sim[i] == least[i])[: k - len(above)])
    return best


def knn8(spark, sf_dir, k: int = 8, scale: int = 1000, block_bytes: int = 32 << 20, tile_bytes: int = 16 << 20):
    """Union of each vector's k nearest by cosine over quantised coordinates, ties by id.

    The vectors are held against each other in blocks of at most block_bytes, each
    broadcast in its turn, in a task as many vectors at once as have tile_bytes of
    similarities; only k candidates a vector and block leave a task."""
    ship(spark)
    quant = F.transform("embedding", lambda v: F.floor(v.cast("double") * scale).cast("long"))
    vec = table(spark, sf_dir, "embeddings", ["vec_id", "embedding"]).select(F.col("vec_id").cast("long").alias("vec_id"), quant.alias("q"))
    row_bytes = 8 * 64
    blocks = max(1, -(-vec.count() * row_bytes // block_bytes))
    found = None
    for b in range(blocks):
        part = vec if blocks == 1 else vec.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == b)
        held = spark.sparkContext.broadcast(_vectors(part.orderBy("vec_id").toArrow()))

        def near(batches, held=held):
            ids, m = held.value
            root = np.sqrt((m * m).sum(1))
            tall = max(1, tile_bytes // (8 * max(1, len(ids))))
            for batch in batches:
                whole = pa.table([batch.column(0), batch.column(1)], ["vec_id", "q"])
                for lo in range(0, batch.num_rows if len(ids) else 0, tall):
                    own, q = _vectors(whole.slice(lo, tall))
                    with np.errstate(invalid="ignore"):
                        sim = (q @ m.T) / root
                    sim[np.isnan(sim)] = np.inf  # as both SQL engines order it
                    at = np.minimum(np.searchsorted(ids, own), len(ids) - 1)
                    here = np.flatnonzero(ids[at] == own)
                    sim[here, at[here]] = -np.inf
                    best = _nearest(sim, k)
                    line = np.arange(len(own))[:, None]
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(np.repeat(own, best.shape[1])), pa.array(ids[best].ravel()), pa.array(sim[line, best].ravel())], ["vec_id", "other", "sim"]
                    )

        out = vec.mapInArrow(near, "vec_id long, other long, sim double")
        found = out if found is None else found.unionByName(out)
    if blocks > 1:
        from pyspark.sql.window import Window

        place = F.row_number().over(Window.partitionBy("vec_id").orderBy(F.desc("sim"), "other"))
        found = found.withColumn("p", place).where(F.col("p") <= k)
    return normalise(found, "vec_id", "other")


def doc_line(spark, sf_dir, least: int = 40, most_docs: int = 20):
    docs = table(spark, sf_dir, "documents", ["doc_id", "text"])
    lines = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.explode(F.split("text", "\n")).alias("line")).where(F.char_length("line") >= least)
    lines = lines.select("doc_id", F.sha2("line", 256).alias("line")).distinct()
    rare = lines.groupBy("line").agg(F.count("*").alias("n")).where(f"n between 2 and {most_docs}").select("line")
    return _pairs_on(lines.join(rare, "line", "left_semi"), "line", "doc_id").select("src", "dst").distinct()


def page_href2(spark, sf_dir):
    pages = table(spark, sf_dir, "pages", ["page_id", "html"])
    links = pages.select(F.col("page_id").cast("long").alias("page_id"), F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("href"))
    return _pairs_on(links, "href", "page_id").groupBy("src", "dst").agg(F.count("*").alias("n")).where("n >= 2").select("src", "dst")


def rmat(spark: SparkSession, scale: int, avg_degree: int = 20, seed: int = 7, quadrants=(0.57, 0.19, 0.19), keys: DataFrame | None = None) -> DataFrame:
    """Recursive-matrix graph with 2**scale vertices; each bit of an edge picks a quadrant by hash.
    keys: a table whose one column has a key for each edge to draw, in place of 0 .. m-1."""
    m = (1 << scale) * avg_degree // 2
    a, b, c = quadrants
    df = spark.range(m) if keys is None else keys.toDF("id")
    src, dst = F.lit(0).cast("long"), F.lit(0).cast("long")
    for bit in range(scale):
        draw = F.pmod(F.xxhash64("id", F.lit(seed * 1000 + bit)), F.lit(1 << 30)) / float(1 << 30)
        right = ((draw >= a) & (draw < a + b)) | (draw >= a + b + c)
        down = draw >= a + b
        src = src * 2 + down.cast("long")
        dst = dst * 2 + right.cast("long")
    return normalise(df.select(src.alias("src"), dst.alias("dst")))


def read_edge_list(spark: SparkSession, path: str, fmt: str = "csv", sep: str = ",") -> DataFrame:
    """Edges from csv, json, orc, parquet or text files with an explicit schema."""
    schema = "src long, dst long"
    if fmt == "csv":
        raw = spark.read.schema(schema).option("sep", sep).csv(path)
    elif fmt == "text":
        part = F.split(F.trim("value"), r"\s+")
        raw = spark.read.text(path).select(part[0].cast("long").alias("src"), part[1].cast("long").alias("dst"))
    else:
        raw = spark.read.schema(schema).format(fmt).load(path)
    return normalise(raw)


def read_adjacency_text(spark: SparkSession, path: str) -> DataFrame:
    """Edges from lines 'id n1 n2 ...'."""
    part = F.split(F.trim("value"), r"\s+")
    rows = spark.read.text(path).select(part.alias("part")).select(F.col("part")[0].cast("long").alias("src"), F.slice("part", 2, F.size("part")).alias("nbrs")).select("src", F.explode("nbrs").alias("dst"))
    return normalise(rows.where("dst <> ''"))


def part_labels(spark, sf_dir, column: str = "p_type"):
    return label_dictionary(table(spark, sf_dir, "part", ["p_partkey", column]), "p_partkey", column)[0]


BUILDERS = {
    "copart_r": copart_r, "copart_full": copart_full, "copart_2": copart_2, "nextline": nextline, "supp_coorder": supp_coorder, "comin": comin,
    "custpart_top": custpart_top, "tree": tree, "knn8": knn8, "doc_line": doc_line, "page_href2": page_href2,
}


def load(spark: SparkSession, sf_dir: str, name: str, label: str | None = None) -> PropertyGraph:
    edges = BUILDERS[name](spark, sf_dir)
    return PropertyGraph.of(edges, part_labels(spark, sf_dir, label) if label else None)


LISTS = {"copart_full": copart_lists}


def load_lists(spark: SparkSession, sf_dir: str, name: str) -> PropertyGraph:
    """The graph by its neighbour lists, which are stored; edges are read from them."""
    lists = keep(LISTS[name](spark, sf_dir), "lists")
    edges = lists.select(F.col("id").alias("src"), F.explode("nbrs").alias("dst")).where("src < dst")
    return PropertyGraph(edges, lists=lists)


def _shared(key: str, node: str, source: str, having: str = "") -> str:
    return (
        f"SELECT x.n AS src, y.n AS dst FROM (SELECT DISTINCT {key} AS k, {node} AS n FROM {source}) x "
        f"JOIN (SELECT DISTINCT {key} AS k, {node} AS n FROM {source}) y ON x.k = y.k AND x.n < y.n GROUP BY 1, 2 {having}"
    )


SQL = {
    "copart_r": _shared("l_orderkey", "l_partkey", "lineitem WHERE l_returnflag = 'R'"),
    "copart_full": _shared("l_orderkey", "l_partkey", "lineitem"),
    "copart_2": _shared("l_orderkey", "l_partkey", "lineitem", "HAVING count(*) >= 2"),
    "nextline": "SELECT DISTINCT least(a.l_partkey, b.l_partkey) AS src, greatest(a.l_partkey, b.l_partkey) AS dst FROM lineitem a JOIN lineitem b "
    "ON a.l_orderkey = b.l_orderkey AND a.l_linenumber + 1 = b.l_linenumber WHERE a.l_partkey <> b.l_partkey",
    "supp_coorder": _shared("l_orderkey", "l_suppkey", "lineitem"),
    "comin": _shared("date_trunc('minute', ts)", "user_id", "events"),
    "custpart_top": "SELECT DISTINCT o_custkey AS src, l_partkey + 100000000 AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' AND l_quantity >= 40",
    "tree": "SELECT DISTINCT (n_regionkey + 1000)::BIGINT AS src, (n_nationkey + 2000)::BIGINT AS dst FROM nation UNION SELECT DISTINCT c_nationkey + 2000, c_custkey + 10000 FROM customer",
    "knn8": "SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM (SELECT x.vec_id AS a, y.vec_id AS b, row_number() OVER (PARTITION BY x.vec_id ORDER BY "
    "list_dot_product(x.q, y.q) / sqrt(list_dot_product(y.q, y.q)) DESC, y.vec_id) AS p FROM (SELECT vec_id, list_transform(embedding, lambda v: floor(v::DOUBLE * 1000)) AS q FROM embeddings) x "
    "JOIN (SELECT vec_id, list_transform(embedding, lambda v: floor(v::DOUBLE * 1000)) AS q FROM embeddings) y ON x.vec_id <> y.vec_id) WHERE p <= 8",
    "doc_line": "SELECT DISTINCT x.doc_id AS src, y.doc_id AS dst FROM (SELECT DISTINCT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) x JOIN "
    "(SELECT DISTINCT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) y ON x.line = y.line AND x.doc_id < y.doc_id JOIN "
    "(SELECT line FROM (SELECT DISTINCT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 40 GROUP BY line HAVING count(*) BETWEEN 2 AND 20) r ON x.line = r.line",
    "page_href2": _shared("href", "page_id", "(SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages)", "HAVING count(*) >= 2"),
}
