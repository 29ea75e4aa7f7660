"""Graphs from the given tables, readers and writers of edge tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from localcomm.functions.sets import canonical
from localcomm.operators.graph import attribute_graph, combined_graph, project_bipartite, structure_graph


@dataclass
class Graph:
    nodes: DataFrame
    edges: DataFrame

    def combined(self, floor: float = 0.05) -> DataFrame:
        return combined_graph(attribute_graph(self.nodes, self.edges, floor))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _words(column, least: int = 1):
    return F.filter(F.split(F.lower(column), "[^a-z]+"), lambda w: F.length(w) >= least)


def parts(spark: SparkSession, sf_dir: str) -> Graph:
    """Parts returned on one order; sets of brand, type, size bucket and name words."""
    # A large table may lie in one file of few row groups, which few tasks would read and canonicalise.
    p = table(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type", "p_size", "p_name").repartition(int(spark.sparkContext.defaultParallelism) * 2)
    attrs = F.concat(F.array("p_brand", "p_type", F.concat(F.lit("size"), F.floor(F.col("p_size") / 10).cast("string"))), _words(F.col("p_name")))
    lines = table(spark, sf_dir, "lineitem").where("l_returnflag = 'R'").select("l_partkey", "l_orderkey")
    return Graph(p.select(F.col("p_partkey").alias("node"), canonical(attrs).alias("attrs")), project_bipartite(lines, "l_partkey", "l_orderkey").select("src", "dst"))


def docs(spark: SparkSession, sf_dir: str, most: int = 20) -> Graph:
    """Documents sharing a normalised line that 2..most documents hold; sets of their 20 rarest long words with df of 2 or more."""
    d = table(spark, sf_dir, "documents").select("doc_id", "text")
    lines = d.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.md5(F.lower(F.trim("line"))).alias("h")).distinct()
    words = d.select("doc_id", F.explode(F.array_distinct(_words(F.col("text"), 6))).alias("word"))
    df = words.groupBy("word").agg(F.count(F.lit(1)).alias("df")).where("df > 1")
    w = Window.partitionBy("doc_id").orderBy("df", "word")
    rare = words.join(df, "word").withColumn("at", F.row_number().over(w)).where("at <= 20").groupBy("doc_id").agg(F.collect_set("word").alias("attrs"))
    nodes = d.select(F.col("doc_id").alias("node")).join(rare.withColumnRenamed("doc_id", "node"), "node", "left").select("node", canonical(F.col("attrs")).alias("attrs"))
    return Graph(nodes, project_bipartite(lines, "doc_id", "h", max_group=most).select("src", "dst"))


def pages(spark: SparkSession, sf_dir: str, most: int = 50) -> Graph:
    """Pages sharing a link target of 2..most pages; sets of the words of the visible text."""
    p = table(spark, sf_dir, "pages").select("page_id", "html")
    links = p.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("to"))
    text = F.regexp_replace("html", "<[^>]*>", " ")
    return Graph(p.select(F.col("page_id").alias("node"), canonical(_words(text)).alias("attrs")), project_bipartite(links, "page_id", "to", max_group=most).select("src", "dst"))


def users(spark: SparkSession, sf_dir: str) -> Graph:
    """Users with the same props in the same hour; sets of event type and props."""
    e = table(spark, sf_dir, "events")
    meet = e.select("user_id", F.concat_ws("|", F.date_trunc("hour", "ts").cast("string"), "props").alias("g"))
    nodes = e.groupBy(F.col("user_id").alias("node")).agg(F.collect_set(F.concat("event_type", "props")).alias("attrs"))
    return Graph(nodes.select("node", canonical(F.col("attrs")).alias("attrs")), project_bipartite(meet, "user_id", "g").select("src", "dst"))


def customers(spark: SparkSession, sf_dir: str) -> Graph:
    """Customers of one nation who bought the same part; sets of segment, nation, region and balance bucket."""
    c = table(spark, sf_dir, "customer")
    n = table(spark, sf_dir, "nation").join(F.broadcast(table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")  # 25 rows
    attrs = F.array("c_mktsegment", "n_name", "r_name", F.concat(F.lit("bal"), F.floor(F.col("c_acctbal") / 1000).cast("string")))
    nodes = c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("c_custkey").alias("node"), canonical(attrs).alias("attrs"))
    bought = table(spark, sf_dir, "orders").join(table(spark, sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey"))
    g = bought.select("c_custkey", F.concat_ws("|", "c_nationkey", "l_partkey").alias("g"))
    return Graph(nodes, project_bipartite(g, "c_custkey", "g").select("src", "dst"))


#: Rows of a block of vectors.
BLOCK = 2048


def vectors(spark: SparkSession, sf_dir: str, k: int = 5, top: int = 8) -> Graph:
    """Each vector's k nearest by cosine, made undirected; sets of the signed places of its largest components.

    All rows are asked against all rows, in blocks of about BLOCK: a task holds two blocks and the matrix of their scores.
    """
    import numpy as np
    import pandas as pd

    v = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("node"), F.col("embedding").cast("array<double>").alias("x"))
    size = F.transform("x", lambda a, i: F.struct(F.round(-F.abs(a), 9).alias("m"), i.alias("i"), F.when(a < 0, "-").otherwise("+").alias("s")))
    attrs = F.transform(F.slice(F.array_sort(size), 1, top), lambda t: F.concat(t["s"], t["i"].cast("string")))
    v = v.withColumn("block", F.pmod(F.xxhash64("node"), F.lit(max(1, -(-v.count() // BLOCK)))).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.lit(max(0, -(-v.count() // BLOCK) - 1))))
    left, right = v.select(F.col("block").alias("b"), every.alias("c"), "node", "x"), v.select(every.alias("b"), F.col("block").alias("c"), "node", "x")

    def near(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a) or not len(b):
            return pd.DataFrame({"src": [], "dst": [], "cos": []})
        x, y = (np.stack(f["x"].to_numpy()) for f in (a, b))
        x, y = (m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-12) for m in (x, y))
        ids, s = b["node"].to_numpy(), np.round(x @ y.T, 9)
        s[a["node"].to_numpy()[:, None] == ids[None, :]] = -2
        order = np.argsort(-s, axis=1, kind="stable")[:, : k + 1]
        return pd.DataFrame({"src": np.repeat(a["node"].to_numpy(), order.shape[1]), "dst": ids[order].ravel(), "cos": np.take_along_axis(s, order, 1).ravel()})

    found = left.groupBy("b", "c").cogroup(right.groupBy("b", "c")).applyInPandas(near, "src long, dst long, cos double").where("cos > -2")
    w = Window.partitionBy("src").orderBy(F.desc("cos"), "dst")
    best = found.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k)
    return Graph(v.select("node", canonical(attrs).alias("attrs")), structure_graph(best))


def bipartite(spark: SparkSession, sf_dir: str) -> DataFrame:
    """customer, part: who bought what."""
    return table(spark, sf_dir, "orders").join(table(spark, sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).select(F.col("o_custkey").alias("customer"), F.col("l_partkey").alias("part")).distinct()


GRAPHS = {"parts": parts, "docs": docs, "pages": pages, "users": users, "customers": customers, "vectors": vectors}


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", directed: bool = False) -> DataFrame:
    """Edges of a file of pairs: parquet, csv (header), json, or text with two ids a line, # for comments."""
    if fmt == "text":
        parts_ = F.split(F.trim("value"), r"\s+")
        pairs = spark.read.text(path).where("value NOT LIKE '#%' AND trim(value) <> ''").select(F.try_element_at(parts_, F.lit(1)).cast("long").alias("src"), F.try_element_at(parts_, F.lit(2)).cast("long").alias("dst"))
    else:
        schema = "src LONG, dst LONG"
        reader = spark.read.schema(schema)
        pairs = reader.option("header", True).csv(path) if fmt == "csv" else reader.json(path) if fmt == "json" else spark.read.parquet(path)
    return structure_graph(pairs, directed=directed)


def write_table(df: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), buckets: int = 0, by: str = "src") -> None:
    """Write to parquet, csv, json or noop; with buckets as a bucketed table named by `path`."""
    w = df.write.mode("overwrite")
    if partition_by:
        w = w.partitionBy(*partition_by)
    if buckets:
        w.bucketBy(buckets, by).sortBy(by).format("parquet").saveAsTable(path)
    elif fmt == "noop":
        w.format("noop").save()
    else:
        (w.option("header", True) if fmt == "csv" else w).format(fmt).save(path)
