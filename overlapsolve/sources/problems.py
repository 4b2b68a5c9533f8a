"""Systems carried by the given tables. Each returns (entries, rhs) and what its partitions need."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from overlapsolve.session import checkpoint, discard
from overlapsolve.sources.mesh import stencil_entries

#: The calendar that the grids cover: weeks from a Monday, months from January, hours from the new year.
FIRST_WEEK, WEEKS, QUANTITIES = "1995-01-02", 357, 50
FIRST_MONTH, MONTHS, DISCOUNTS = (1995, 1), 83, 11
FIRST_HOUR, HOURS = "2024-01-01", 720


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def inside(x: Column, low: Column | int, n: Column | int, what: str) -> Column:
    """x, which must be null or among the n whole numbers from low on; a row outside the calendar or the lattice is an error."""
    return F.when(x.isNull() | ((x >= low) & (x < low + n)), x).otherwise(F.raise_error(F.concat(F.lit(f"{what} out of range: "), x.cast("string"))).cast("long"))


def _filled(spark: SparkSession, n: int, cells: DataFrame) -> DataFrame:
    """(i, x) over 0..n-1, 0 where no cell has rows."""
    return spark.range(n).select(F.col("id").alias("i")).join(cells, "i", "left").select("i", F.coalesce("x", F.lit(0.0)).alias("x"))


def week_of(date: Column) -> Column:
    return F.floor(F.datediff(date, F.lit(FIRST_WEEK)) / 7).cast("long")


def grid2d_rhs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of lineitem by ship week and quantity."""
    node = inside(week_of(F.col("l_shipdate")), 0, WEEKS, "week") * QUANTITIES + inside(F.col("l_quantity").cast("long"), 1, QUANTITIES, "quantity") - 1
    cells = load_table(spark, sf_dir, "lineitem").select(node.alias("i")).groupBy("i").agg(F.count("*").cast("double").alias("x"))
    return _filled(spark, WEEKS * QUANTITIES, cells)


def grid2d_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(i): the ship weeks and quantities that rows of lineitem have."""
    node = inside(week_of(F.col("l_shipdate")), 0, WEEKS, "week") * QUANTITIES + inside(F.col("l_quantity").cast("long"), 1, QUANTITIES, "quantity") - 1
    return load_table(spark, sf_dir, "lineitem").select(node.alias("i")).where("i is not null").distinct()


def grid3d_rhs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of lineitem by ship month, quantity and discount in hundredths."""
    date = F.col("l_shipdate")
    month = (F.year(date) - FIRST_MONTH[0]) * 12 + F.month(date) - FIRST_MONTH[1]
    node = (inside(month.cast("long"), 0, MONTHS, "month") * QUANTITIES + inside(F.col("l_quantity").cast("long"), 1, QUANTITIES, "quantity") - 1) * DISCOUNTS + inside(F.round(100 * F.col("l_discount")).cast("long"), 0, DISCOUNTS, "discount")
    cells = load_table(spark, sf_dir, "lineitem").select(node.alias("i")).groupBy("i").agg(F.count("*").cast("double").alias("x"))
    return _filled(spark, MONTHS * QUANTITIES * DISCOUNTS, cells)


def shipgrid2d(spark: SparkSession, sf_dir: str, sigma: float = 1.0) -> tuple[DataFrame, DataFrame]:
    return stencil_entries(spark, (WEEKS, QUANTITIES), 4 + sigma), grid2d_rhs(spark, sf_dir)


def shipgrid3d(spark: SparkSession, sf_dir: str, sigma: float = 1.0) -> tuple[DataFrame, DataFrame]:
    return stencil_entries(spark, (MONTHS, QUANTITIES, DISCOUNTS), 6 + sigma), grid3d_rhs(spark, sf_dir)


def hour_index(ts: Column, origin: str = FIRST_HOUR) -> Column:
    return F.floor((F.unix_timestamp(ts) - F.unix_timestamp(F.lit(origin).cast("timestamp"))) / 3600).cast("long")


def chain_rhs(spark: SparkSession, sf_dir: str, scale: float = 100.0) -> DataFrame:
    """Summed event values by hour, divided by `scale`."""
    e = load_table(spark, sf_dir, "events").select(inside(hour_index(F.col("ts")), 0, HOURS, "hour").alias("i"), "value")
    return _filled(spark, HOURS, e.groupBy("i").agg((F.sum("value") / scale).alias("x")))


def eventchain(spark: SparkSession, sf_dir: str, sigma: float = 1.0) -> tuple[DataFrame, DataFrame]:
    return stencil_entries(spark, (HOURS,), 2 + sigma), chain_rhs(spark, sf_dir)


#: Where the ids of each level of the tree begin.
TREE_BASE = {"region": 0, "nation": 1_000, "customer": 1_000_000, "orders": 1_000_000_000}


def tree_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(i, parent, nation, f): regions, nations, customers and orders; f in thousands, 0 on the upper levels."""
    region, nation, customer, orders = (load_table(spark, sf_dir, t) for t in ("region", "nation", "customer", "orders"))
    at = lambda level, key: (F.col(key).cast("long") + TREE_BASE[level])
    none = F.lit(None).cast("long")
    zero = F.lit(0.0)
    lowest = nation.groupBy("n_regionkey").agg(F.min("n_nationkey").cast("int").alias("nation"))
    roots = region.join(lowest, region.r_regionkey == lowest.n_regionkey, "left").select(at("region", "r_regionkey").alias("i"), none.alias("parent"), F.coalesce("nation", F.lit(0)).alias("nation"), zero.alias("f"))
    second = nation.select(at("nation", "n_nationkey"), at("region", "n_regionkey"), F.col("n_nationkey").cast("int"), zero)
    third = customer.select(at("customer", "c_custkey"), at("nation", "c_nationkey"), F.col("c_nationkey").cast("int"), F.col("c_acctbal") / 1000)
    homes = customer.select("c_custkey", "c_nationkey")
    leaves = orders.join(homes, orders.o_custkey == homes.c_custkey).select(at("orders", "o_orderkey"), at("customer", "o_custkey"), F.col("c_nationkey").cast("int"), F.col("o_totalprice") / 1000)
    return roots.union(second).union(third).union(leaves)


def laplacian(edges: DataFrame, sigma: float = 1.0, relative: bool = False) -> DataFrame:
    """(i, j, a) from undirected weighted edges (u, v, w), each given once: degree + sigma, or degree * (1 + sigma), on the diagonal."""
    both = edges.select(F.col("u").alias("i"), F.col("v").alias("j"), F.col("w").alias("w")).union(edges.select("v", "u", "w")).groupBy("i", "j").agg(F.sum("w").alias("w"))
    degree = both.groupBy("i").agg(F.sum("w").alias("d"))
    diagonal = F.col("d") * F.lit(1 + sigma) if relative else F.col("d") + F.lit(float(sigma))
    return both.select("i", "j", (-F.col("w")).alias("a")).union(degree.select("i", F.col("i").alias("j"), diagonal.alias("a")))


def startree(spark: SparkSession, sf_dir: str, sigma: float = 1.0) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(entries, rhs, owner by nation)."""
    nodes = tree_nodes(spark, sf_dir)
    edges = nodes.where("parent is not null").select(F.col("i").alias("u"), F.col("parent").alias("v"), F.lit(1.0).alias("w"))
    return laplacian(edges, sigma), nodes.select("i", F.col("f").alias("x")), nodes.select("i", F.col("nation").alias("p"))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, anchor, w): how often a page links to each address."""
    pages = load_table(spark, sf_dir, "pages")
    anchors = F.regexp_extract_all("html", F.lit(r'<a href="([^"]*)"'), 1)
    return pages.select("page_id", F.explode(anchors).alias("anchor")).groupBy("page_id", "anchor").agg(F.count("*").cast("double").alias("w"))


def pagegraph(spark: SparkSession, sf_dir: str, sigma: float = 1.0) -> tuple[DataFrame, DataFrame]:
    """Grounded bipartite Laplacian of pages and distinct anchors; pages carry text length / 1000.

    Anchors are numbered by a hash, so no global sort is needed; ids of pages are even, those of anchors odd.
    """
    edges = page_links(spark, sf_dir).select((2 * F.col("page_id")).alias("u"), (F.shiftrightunsigned(F.xxhash64("anchor"), 2) * 2 + 1).alias("v"), "w")
    entries = laplacian(edges, sigma, relative=True)
    weight = load_table(spark, sf_dir, "pages").select((2 * F.col("page_id")).alias("i"), (F.length("html") / 1000.0).alias("x"))
    return entries, entries.select("i").distinct().join(weight, "i", "left").select("i", F.coalesce("x", F.lit(0.0)).alias("x"))


def chat_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(u, v, w): consecutive turns of each conversation; a node is conv_id * 1000 + turn."""
    c = load_table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("v"), "conv_id", "turn")
    before = F.lag("v").over(Window.partitionBy("conv_id").orderBy("turn"))
    return c.select(before.alias("u"), "v", F.lit(1.0).alias("w")).where("u is not null")


def chatchain(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(entries, rhs, owner): chains that don't couple; conversations are dealt to 4 parts."""
    c = load_table(spark, sf_dir, "conversations")
    node = (F.col("conv_id") * 1000 + F.col("turn")).alias("i")
    nodes = c.select(node, F.length("text").cast("double").alias("x"))
    couplings = laplacian(chat_edges(spark, sf_dir), 1.0)
    alone = nodes.join(couplings, "i", "left_anti").select("i", F.col("i").alias("j"), F.lit(1.0).alias("a"))
    return couplings.union(alone), nodes, c.select(node, F.pmod("conv_id", F.lit(4)).cast("int").alias("p"))


def docgraph(spark: SparkSession, sf_dir: str, sigma: float = 0.1) -> tuple[DataFrame, DataFrame]:
    """Near-copy graph of documents, with labelled qualities eliminated as known values.

    Documents that share one of their 4 smallest word-window hashes are tied to the bucket's smallest id, with the
    number of shared hashes as weight, so a bucket of k documents makes k - 1 edges.
    """
    docs = load_table(spark, sf_dir, "documents")
    w = F.split(F.lower(F.coalesce("text", F.lit(""))), r"\s+")
    # Hashed word by word, a null leaving the hash as it is: the hash of the window as a list, without a copy of it.
    grams = F.transform(F.sequence(F.lit(0), F.greatest(F.size("w") - 5, F.lit(0))), lambda k: F.xxhash64(*[F.get("w", k + b) for b in range(5)]))
    # Written, as what follows reads it several times and each time would hash all texts again.
    low = checkpoint(docs.select("doc_id", w.alias("w")).select("doc_id", F.explode(F.slice(F.sort_array(F.array_distinct(grams)), 1, 4)).alias("h")))
    first = low.groupBy("h").agg(F.min("doc_id").alias("u"), F.count("*").alias("n")).where("n > 1")
    edges = checkpoint(low.join(first.select("h", "u"), "h").where("doc_id <> u").groupBy("u", F.col("doc_id").alias("v")).agg(F.count("*").cast("double").alias("w")))
    discard(low)
    couplings = laplacian(edges, sigma, relative=True)
    ids = docs.select(F.col("doc_id").alias("i"))
    alone = ids.join(couplings, "i", "left_anti").select("i", F.col("i").alias("j"), F.lit(1.0).alias("a"))
    known = load_table(spark, sf_dir, "labels").select(F.col("doc_id").alias("i"), F.col("quality").cast("double").alias("x"))
    return eliminate_dirichlet(couplings.union(alone), ids.select("i", F.lit(0.0).alias("x")), known)


def eliminate_dirichlet(entries: DataFrame, f: DataFrame, known: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(entries, f) with rows of known values replaced by x = value and their columns moved to the right-hand side."""
    marked = entries.join(known.select(F.col("i").alias("j"), F.col("x").alias("xj")), "j", "left").join(known.select("i", F.col("x").alias("xi")), "i", "left")
    free = marked.where("xi is null")
    moved = free.where("xj is not null").groupBy("i").agg(F.sum(F.col("a") * F.col("xj")).alias("m"))
    rest = free.where("xj is null").select("i", "j", "a").union(known.select("i", F.col("i").alias("j"), F.lit(1.0).alias("a")))
    new = f.join(moved, "i", "left").join(known.withColumnRenamed("x", "k"), "i", "left").select("i", F.coalesce("k", F.col("x") - F.coalesce("m", F.lit(0.0))).alias("x"))
    return rest, new


def _nearest(k: int, here: pa.Table, other: pa.Table, block: int = 256) -> pa.Table:
    """(i, j): for each row of here the k rows of other, itself left out, with the largest inner products, ties to the smaller id.

    Products are summed in order of the components. A matrix product, which rounds otherwise, only tells which can be among
    the largest. A product with a null component or of unequal lengths comes last, one that is no number first.
    """
    i, j = here.column("i").to_numpy(), other.column("j").to_numpy()
    lists = [t.column("vector").to_pylist() for t in (here, other)]
    width = max((len(v) for x in lists for v in x), default=0)
    q, c = (np.array([[0.0 if y is None else y for y in v] + [0.0] * (width - len(v)) for v in x]).reshape(len(x), width) for x in lists)
    sizes = [np.array([-1 if None in v else len(v) for v in x], np.int64) for x in lists]
    plain = all((n == width).all() for n in sizes) and np.isfinite(q).all() and np.isfinite(c).all()
    most = float(np.linalg.norm(c, axis=1).max()) if plain and len(c) else 0.0
    of, to = [], []
    for a in range(0, len(i) if len(j) > 0 else 0, block):
        part = q[a : a + block]
        able = j[None, :] != i[a : a + block, None]
        if plain and len(j) > k + 1:
            rough = np.where(able, part @ c.T, -np.inf)
            least = np.partition(rough, len(j) - k, axis=1)[:, len(j) - k]
            able &= rough >= (least - 1e-13 * width * most * np.linalg.norm(part, axis=1))[:, None]
        row, col = np.nonzero(able)
        s = np.zeros(len(row))
        for d in range(width):
            s += part[row, d] * c[col, d]
        none = (sizes[0][a + row] < 0) | (sizes[0][a + row] != sizes[1][col])
        order = np.lexsort((j[col], np.where(none | np.isnan(s), 0.0, -s), np.where(none, 2, np.where(np.isnan(s), 0, 1)), row))
        row, col = row[order], col[order]
        first = np.arange(len(row)) - np.searchsorted(row, row) < k
        of.append(i[a + row[first]])
        to.append(j[col[first]])
    ends = [np.concatenate([np.zeros(0, np.int64), *x]) for x in (of, to)]
    return pa.table({"i": pa.array(ends[0], pa.int64()), "j": pa.array(ends[1], pa.int64())})


def knn(spark: SparkSession, sf_dir: str, k: int = 8, sigma: float = 1.0, cells: int = 16) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(entries, rhs, owner by label): approximate neighbours within a cell of sign bits and its one-bit neighbours.

    A negative control: the graph isn't local, so overlaps swallow most of it.
    """
    e = load_table(spark, sf_dir, "embeddings").where("embedding is not null")
    bits = max(0, cells.bit_length() - 2)
    code = sum((F.when(F.get("embedding", F.lit(b)) > 0, F.lit(1 << b)).otherwise(0) for b in range(1, bits)), F.when(F.get("embedding", F.lit(0)) > 0, F.lit(1)).otherwise(0))
    base = e.select(F.col("vec_id").alias("i"), "embedding", F.col("label").cast("int").alias("label"), code.alias("cell"))
    probes = F.array(F.col("cell"), *[F.col("cell").bitwiseXOR(F.lit(1 << b)) for b in range(bits)])
    vector = F.col("embedding").cast("array<double>").alias("vector")
    here = base.select("cell", "i", vector)
    other = base.select(F.explode(probes).alias("cell"), F.col("i").alias("j"), vector)
    near = here.groupBy("cell").cogroup(other.groupBy("cell")).applyInArrow(lambda here, other: _nearest(k, here, other), "i long, j long")
    edges = near.select(F.least("i", "j").alias("u"), F.greatest("i", "j").alias("v")).distinct().withColumn("w", F.lit(1.0))
    entries = laplacian(edges, sigma, relative=True)
    lone = base.join(entries, "i", "left_anti").select("i", F.col("i").alias("j"), F.lit(1.0).alias("a"))
    return entries.union(lone), base.select("i", F.when(F.col("label") == 0, 1.0).otherwise(0.0).alias("x")), base.select("i", F.col("label").alias("p"))


def cosupply(spark: SparkSession, sf_dir: str, sigma: float = 1.0) -> tuple[DataFrame, DataFrame]:
    """Customers and suppliers that orders tie: a hub graph, the second negative control. Suppliers have odd ids."""
    items, orders = load_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey"), load_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    pairs = items.join(orders, items.l_orderkey == orders.o_orderkey).groupBy("o_custkey", "l_suppkey").agg(F.count("*").cast("double").alias("w"))
    entries = laplacian(pairs.select((2 * F.col("o_custkey")).alias("u"), (2 * F.col("l_suppkey") + 1).alias("v"), "w"), sigma, relative=True)
    balance = load_table(spark, sf_dir, "customer").select((2 * F.col("c_custkey")).alias("i"), (F.col("c_acctbal") / 1000).alias("x"))
    return entries, entries.select("i").distinct().join(balance, "i", "left").select("i", F.coalesce("x", F.lit(0.0)).alias("x"))
