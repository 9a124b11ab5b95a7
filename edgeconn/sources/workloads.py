"""Graphs on the given tables, as (a, b) pairs before canonical form."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from edgeconn.operators import blocks as X
from edgeconn.operators.graph import Graph, canonical_edges, encode_vertices, numbered
from edgeconn.plans.staging import stage
from edgeconn.sources.tables import table

NATIONS = 25
#: Customers of a nation that meet as many others in one task.
CELL = 1500


def part_supplier(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").select((2 * F.col("l_partkey")).alias("a"), (2 * F.col("l_suppkey") + 1).alias("b"))


def customer_supplier(spark: SparkSession, d: str) -> DataFrame:
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_suppkey")
    return table(spark, d, "orders").select("o_orderkey", "o_custkey").join(lines, F.col("o_orderkey") == F.col("l_orderkey")).select((2 * F.col("o_custkey")).alias("a"), (2 * F.col("l_suppkey") + 1).alias("b"))


def same_order(spark: SparkSession, d: str, key: str) -> DataFrame:
    """Pairs of parts or suppliers in one order; an order has few lines."""
    one = table(spark, d, "lineitem").select("l_orderkey", F.col(key).alias("a")).distinct()
    two = one.withColumnRenamed("a", "b")
    return one.join(two, "l_orderkey").filter("a < b").select("a", "b")


def ranked_customers(spark: SparkSession, d: str) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy("c_nationkey").orderBy("c_custkey")) - 1
    return table(spark, d, "customer").select(F.col("c_custkey").alias("v"), F.col("c_nationkey").alias("nation"), rank.alias("r"))


def nation_cliques(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of customers of one nation. A nation of many is dealt into cells,
    and each two cells meet in a task: there are few nations, and without it
    a task would make all pairs of one. Two cells meet once, as (i, j) with
    i <= j."""
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("a"), "c_nationkey")
    most = c.groupBy("c_nationkey").count().agg(F.max("count")).first()[0] or 0
    cells = -(-most // CELL)
    if cells < 2:
        return c.join(c.withColumnRenamed("a", "b"), "c_nationkey").filter("a < b").select("a", "b")
    c = c.withColumn("own", F.pmod(F.xxhash64("a"), F.lit(cells)).cast("int"))
    on = ["c_nationkey", "i", "j"]
    tasks = min(NATIONS * cells * (cells + 1) // 2, 4000)
    left = c.select("a", "c_nationkey", F.col("own").alias("i"), F.explode(F.sequence("own", F.lit(cells - 1))).alias("j")).repartition(tasks, *on)
    right = c.select(F.col("a").alias("b"), "c_nationkey", F.explode(F.sequence(F.lit(0), "own")).alias("i"), F.col("own").alias("j")).repartition(tasks, *on)
    return left.join(right, on).filter("i < j OR a < b").select("a", "b")


def nation_blocks(spark: SparkSession, d: str, links: DataFrame | None = None) -> DataFrame | None:
    """The pairs of ``nation_cliques`` and ``links`` (a, b, gap) as blocks, for
    nations of several cells: the meetings of cells, dealt to tasks in order, so
    that a task has few vertices. None where no nation has several."""
    c = table(spark, d, "customer").select("c_custkey", "c_nationkey").filter("c_custkey IS NOT NULL AND c_nationkey IS NOT NULL")
    row = c.groupBy("c_nationkey").count().agg(F.max("count").alias("most"), F.sum(F.col("count").cast("double") ** 2).alias("ends")).first()
    cells = -(-(row.most or 0) // CELL)
    if cells < 2:
        return None

    def ids(x) -> bytes:
        return x.sort_values().to_numpy("int64").tobytes()

    own = c.withColumn("own", F.pmod(F.xxhash64("c_custkey"), F.lit(cells)).cast("int"))
    packed = stage(own.groupBy("c_nationkey", "own").applyInPandas(lambda p: p.iloc[:1][["c_nationkey", "own"]].assign(ids=[ids(p["c_custkey"])]), "c_nationkey long, own int, ids binary"), "cells").df
    left, right = packed.toDF("nation", "i", "a"), packed.toDF("nation", "j", "b")
    tasks = max(3 * spark.sparkContext.defaultParallelism, int(row.ends / 2 / X.TASK_EDGES) + 1)
    meet = left.drop("a").join(right.drop("b"), "nation").filter("i <= j")
    meet = meet.withColumn("part", F.ntile(tasks).over(Window.orderBy("nation", "i", "j")) - 1)  # a row for two cells
    kind = F.when(F.col("i") < F.col("j"), X.ACROSS).otherwise(X.WITHIN).alias("kind")
    blocks = meet.join(left, ["nation", "i"]).join(right, ["nation", "j"]).select("part", kind, "a", "b")
    if links is not None:
        pack = lambda p: p.iloc[:1][["part"]].assign(a=[p["a"].to_numpy("int64").tobytes()], b=[p["b"].to_numpy("int64").tobytes()])
        along = links.select(F.pmod("gap", F.lit(tasks)).cast("int").alias("part"), "a", "b").groupBy("part").applyInPandas(pack, "part int, a binary, b binary")
        blocks = blocks.unionByName(along.withColumn("kind", F.lit(X.ALONG)))
    return stage(blocks, "blocks").df


def bridges(spark: SparkSession, d: str, t: int, closed: bool = True, uneven: bool = False) -> DataFrame:
    """(a, b, gap): customers of equal rank under t of nations i and i + 1."""
    c = ranked_customers(spark, d)
    limit = F.lit(t) + F.col("nation") % 2 if uneven else F.lit(t)
    near = c.filter(F.col("r") < limit).select(F.col("v").alias("a"), F.col("nation").alias("gap"), "r")
    far = c.select(F.col("v").alias("b"), ((F.col("nation") + NATIONS - 1) % NATIONS).alias("gap"), "r")
    out = near.join(far, ["gap", "r"]).select("a", "b", "gap")
    return out if closed else out.filter(F.col("gap") < NATIONS - 1)


def nation_ring(spark: SparkSession, d: str, t: int, closed: bool = True, uneven: bool = False) -> DataFrame:
    return nation_cliques(spark, d).unionByName(bridges(spark, d, t, closed, uneven).select("a", "b"))


def nation_circulant(spark: SparkSession, d: str, w: int, t: int) -> DataFrame:
    """Each customer to the next w ranks of the nation, circular, plus bridges."""
    c = ranked_customers(spark, d).withColumn("size", F.count(F.lit(1)).over(Window.partitionBy("nation")))
    step = c.withColumn("s", F.explode(F.sequence(F.lit(1), F.lit(w)))).select(F.col("v").alias("a"), "nation", ((F.col("r") + F.col("s")) % F.col("size")).alias("r"))
    return step.join(c.select(F.col("v").alias("b"), "nation", "r"), ["nation", "r"]).select("a", "b").unionByName(bridges(spark, d, t).select("a", "b"))


def two_block(spark: SparkSession, d: str, t: int) -> DataFrame:
    inner = same_order(spark, d, "l_partkey").filter("a % 2 = b % 2")
    links = spark.range(t).select((2 * F.col("id")).alias("a"), (2 * F.col("id") + 1).alias("b"))
    return inner.unionByName(links)


def user_user(spark: SparkSession, d: str, lags: int = 1) -> DataFrame:
    """(a, b, ts, event_id): users of events at most ``lags`` apart in time.

    The order of all events is one sequence by definition: it is numbered by
    ranges of that order, and an event meets those at most ``lags`` places
    before it by joins on the number, so no task orders them all and a range
    may have fewer events than lags.
    """
    e = table(spark, d, "events").select("event_id", "ts", F.col("user_id").alias("b"))
    placed = numbered(e.withColumn("key", F.struct("ts", "event_id")), "key", "no").drop("key")
    back = placed.select(F.col("b").alias("a"), F.explode(F.sequence(F.col("no") + 1, F.col("no") + lags)).alias("no"))
    return placed.join(back, "no").select("a", "b", "ts", "event_id")


def brand_supplier(spark: SparkSession, d: str) -> DataFrame:
    p = table(spark, d, "part").select("p_partkey", "p_brand")
    brands = p.select("p_brand").distinct().select("p_brand", (2 * (F.dense_rank().over(Window.orderBy("p_brand")) - 1)).alias("a"))  # 25 brands
    lines = table(spark, d, "lineitem").select("l_partkey", "l_suppkey")
    return lines.join(p, F.col("l_partkey") == F.col("p_partkey")).join(brands, "p_brand").select("a", (2 * F.col("l_suppkey") + 1).alias("b"))


def nation_nation(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "customer").select("c_custkey", F.col("c_nationkey").alias("a"))
    s = table(spark, d, "supplier").select("s_suppkey", F.col("s_nationkey").alias("b"))
    o = table(spark, d, "orders").select("o_orderkey", "o_custkey")
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_suppkey")
    return lines.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey")).select("a", "b")


def user_hour(spark: SparkSession, d: str) -> DataFrame:
    """User and hour of events, with text ids, through the dictionary."""
    raw = table(spark, d, "events").select(F.concat(F.lit("u"), F.col("user_id").cast("string")).alias("a"), F.concat(F.lit("h"), F.date_format("ts", "yyyyMMddHH")).alias("b")).distinct()
    return encode_vertices(raw)[0]


def page_links(spark: SparkSession, d: str) -> DataFrame:
    """Pages and the tokens of their links, bipartite, with text ids."""
    links = F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), 1))
    raw = table(spark, d, "pages").select(F.concat(F.lit("p"), F.col("page_id").cast("string")).alias("a"), links.alias("b")).distinct()
    return encode_vertices(raw)[0]


def conversation_paths(spark: SparkSession, d: str) -> DataFrame:
    """Consecutive turns of a conversation, through the dictionary, so that a
    conversation may have any number of turns."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    c = table(spark, d, "conversations").select("conv_id", "turn", F.lead("turn").over(w).alias("after")).filter("after IS NOT NULL")
    name = lambda turn: F.concat(F.col("conv_id").cast("string"), F.lit(":"), F.col(turn).cast("string"))
    return encode_vertices(c.select(name("turn").alias("a"), name("after").alias("b")))[0]


def nearest(e: DataFrame, k: int, block: int = 4096) -> DataFrame:
    """(a, b): the k vectors of greatest cosine of each vector, among all.

    Vectors are dealt into even blocks, each block is multiplied with every
    block, and a task sends on k rows of a vector and block at most. Cosines
    equal to 12 places are ties, which the lesser id wins.
    """
    known = e.filter("vec_id IS NOT NULL AND embedding IS NOT NULL").select("vec_id", "embedding")
    n = max(1, -(-known.count() // block))

    def pack(pdf):
        import numpy as np
        import pandas as pd

        x = np.stack(pdf["embedding"].to_numpy()).astype(np.float64)
        x = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
        order = np.argsort(pdf["vec_id"].to_numpy(), kind="stable")
        return pd.DataFrame({"block": [pdf["block"].iloc[0]], "ids": [pdf["vec_id"].to_numpy(np.int64)[order].tobytes()], "x": [x[order].tobytes()]})

    def near(batches):
        import numpy as np
        import pandas as pd

        for pdf in batches:
            for row in pdf.itertuples():
                ids, other = np.frombuffer(row.ids, np.int64), np.frombuffer(row.ids2, np.int64)
                x, y = np.frombuffer(row.x).reshape(len(ids), -1), np.frombuffer(row.x2).reshape(len(other), -1)
                for i in range(0, len(x), 512):
                    mine = ids[i : i + 512]
                    sim = np.round(x[i : i + 512] @ y.T, 12)
                    sim[mine[:, None] == other[None, :]] = -2
                    top = np.argsort(-sim, axis=1, kind="stable")[:, :k]
                    best = np.take_along_axis(sim, top, 1)
                    real = best.ravel() > -2
                    yield pd.DataFrame({"a": np.repeat(mine, top.shape[1])[real], "b": other[top.ravel()][real], "sim": best.ravel()[real]})

    dealt = known.withColumn("block", F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int"))
    packed = stage(dealt.groupBy("block").applyInPandas(pack, "block int, ids binary, x binary"), "vector-blocks").df
    left = packed.withColumn("to", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).drop("block")
    right = packed.select(F.col("block").alias("to"), F.col("ids").alias("ids2"), F.col("x").alias("x2"))
    pairs = left.join(right, "to").mapInPandas(near, "a long, b long, sim double")
    place = F.row_number().over(Window.partitionBy("a").orderBy(F.desc("sim"), "b"))
    return pairs.withColumn("place", place).filter(F.col("place") <= k).select("a", "b")


def embedding_neighbours(spark: SparkSession, d: str, k: int = 8) -> DataFrame:
    """Mutual k nearest by cosine among all vectors; labels are not read."""
    one = stage(nearest(table(spark, d, "embeddings"), k), "neighbours").df
    return one.join(one.select(F.col("a").alias("b"), F.col("b").alias("a")), ["a", "b"]).filter("a < b").select("a", "b")


def document_shingles(spark: SparkSession, d: str, words: int = 8) -> DataFrame:
    """Documents and the shingles they share with another, bipartite."""
    w = F.split(F.lower("text"), r"\s+")
    hashed = table(spark, d, "documents").select("doc_id", w.alias("w")).filter(F.size("w") >= words)
    sh = hashed.select("doc_id", F.explode(F.transform(F.sequence(F.lit(0), F.size("w") - words), lambda i: F.xxhash64(F.slice("w", i + 1, words)))).alias("h")).distinct()
    shared = sh.groupBy("h").count().filter("count > 1").select("h")
    pairs = sh.join(shared, "h").select(F.concat(F.lit("d"), F.col("doc_id").cast("string")).alias("a"), F.concat(F.lit("s"), F.col("h").cast("string")).alias("b"))
    return encode_vertices(pairs)[0]


ONCE = {"nation_cliques", "nation_ring", "nation_chain", "nation_ring_uneven"}


def graph(spark: SparkSession, d: str, name: str, **params) -> Graph:
    raw = {
        "part_supplier": part_supplier,
        "customer_supplier": customer_supplier,
        "part_part": lambda s, x: same_order(s, x, "l_partkey"),
        "supplier_supplier": lambda s, x: same_order(s, x, "l_suppkey"),
        "nation_cliques": nation_cliques,
        "nation_ring": nation_ring,
        "nation_chain": lambda s, x, t: nation_ring(s, x, t, closed=False),
        "nation_ring_uneven": lambda s, x, t: nation_ring(s, x, t, uneven=True),
        "nation_circulant": nation_circulant,
        "two_block": two_block,
        "user_user": user_user,
        "brand_supplier": brand_supplier,
        "nation_nation": nation_nation,
        "user_hour": user_hour,
        "page_links": page_links,
        "conversation_paths": conversation_paths,
        "embedding_neighbours": embedding_neighbours,
        "document_shingles": document_shingles,
    }[name](spark, d, **params)
    # Of customers with a key each, no two pairs of the nation graphs are equal.
    once = name in ONCE and table(spark, d, "customer").groupBy("c_custkey").count().filter("count > 1").isEmpty()
    return Graph.of(canonical_edges(raw, repeats=not once))


def block_graph(spark: SparkSession, d: str, name: str, **params) -> Graph | None:
    """The same graph by staged blocks, where it is one of large nations."""
    if name not in ONCE or not table(spark, d, "customer").groupBy("c_custkey").count().filter("count > 1").isEmpty():
        return None
    how = {"closed": name != "nation_chain", "uneven": name == "nation_ring_uneven"}
    blocks = nation_blocks(spark, d, None if name == "nation_cliques" else bridges(spark, d, **{**how, **params}))
    return None if blocks is None else Graph.of_blocks(blocks)
