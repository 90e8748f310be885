"""Node attributes and labels from ordinary tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from prunegraph.sources.tables import read

MOST_CATEGORIES = 1000
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]


def formula_features(nodes: DataFrame, width: int = 8) -> DataFrame:
    """Small integers from a rule both engines share."""
    cell = lambda j: (F.pmod(F.col("node_id") * (j + 3) + j * j, F.lit(7)) - 3).cast("double")
    return nodes.select("node_id", F.array(*(cell(j) for j in range(width))).alias("h"))


def one_hot(column, values: list) -> list:
    return [F.when(column == v, 1.0).otherwise(0.0) for v in values]


def categories(df: DataFrame, column: str) -> list:
    """Distinct values in order; for columns whose domain is small by nature, which is checked."""
    found = [r[0] for r in df.select(column).distinct().limit(MOST_CATEGORIES + 1).collect() if r[0] is not None]
    if len(found) > MOST_CATEGORIES:
        raise ValueError(f"{column} has more than {MOST_CATEGORIES} values: hash it instead of one column a value")
    return sorted(found)


def purchase_features(spark: SparkSession, folder: str) -> tuple[DataFrame, int]:
    """Customers (nation, segment, balance) and parts (brand, type, size, price) side by side."""
    c, p = read(spark, folder, "customer"), read(spark, folder, "part")
    segments, brands, types = categories(c, "c_mktsegment"), categories(p, "p_brand"), categories(p, "p_type")
    top = p.agg(F.max("p_retailprice")).first()[0]
    mine = [*one_hot(F.col("c_nationkey"), list(range(25))), *one_hot(F.col("c_mktsegment"), segments), F.col("c_acctbal") / 10000, F.lit(1.0)]
    theirs = [*one_hot(F.col("p_brand"), brands), *one_hot(F.col("p_type"), types), F.col("p_size") / 50, F.col("p_retailprice") / float(top), F.lit(1.0)]
    zero = lambda n: [F.lit(0.0)] * n
    a = c.select((F.col("c_custkey") * 4).alias("node_id"), F.array(*mine, *zero(len(theirs))).alias("h"))
    b = p.select((F.col("p_partkey") * 4 + 1).alias("node_id"), F.array(*zero(len(mine)), *theirs).alias("h"))
    return a.unionByName(b), len(mine) + len(theirs)


def token_features(docs: DataFrame, width: int = 64, id_column: str = "doc_id") -> DataFrame:
    """log1p counts of hashed tokens, unit length."""
    words = F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda w: F.length(w) > 0)
    rows = docs.select(F.col(id_column).alias("node_id"), F.explode(words).alias("t")).withColumn("ch", (F.crc32(F.col("t").cast("binary")) % width).cast("int"))
    cells = rows.groupBy("node_id").pivot("ch", list(range(width))).count()
    h = F.array(*(F.log1p(F.coalesce(F.col(f"`{j}`"), F.lit(0)).cast("double")) for j in range(width)))
    norm = F.sqrt(F.aggregate("h", F.lit(0.0), lambda s, x: s + x * x))
    return cells.select("node_id", h.alias("h")).select("node_id", F.transform("h", lambda x: F.coalesce(F.try_divide(x, norm), F.lit(0.0))).alias("h"))


def shape_columns(text="text") -> dict:
    """Counts that describe how a text looks."""
    t = F.col(text)
    only = lambda pattern: F.length(F.regexp_replace(t, pattern, ""))
    words = F.filter(F.split(t, "[ \n]+"), lambda w: F.length(w) > 0)
    return {
        "chars": F.length(t).cast("long"),
        "digits": only("[^0-9]").cast("long"),
        "uppers": only("[^A-Z]").cast("long"),
        "words": F.size(words).cast("long"),
        "distinct_words": F.size(F.array_distinct(words)).cast("long"),
        "lines": F.size(F.split(t, "\n")).cast("long"),
    }


def shape_features(docs: DataFrame, id_column: str = "doc_id") -> DataFrame:
    s = docs.select(F.col(id_column).alias("node_id"), *(c.alias(n) for n, c in shape_columns().items()))
    n = F.greatest(F.col("chars"), F.lit(1))
    other = F.col("chars") - F.col("digits") - F.col("uppers")
    cells = [F.log1p(F.col("chars")), F.col("digits") / n, F.col("uppers") / n, other / n, F.col("distinct_words") / F.greatest("words", F.lit(1)), F.col("lines") / n, F.col("chars") / F.greatest("words", F.lit(1)) / 10, F.when(F.col("words") < 20, 1.0).otherwise(0.0)]
    return s.select("node_id", F.array(*(c.cast("double") for c in cells)).alias("h"))


def standardize(feats: DataFrame, width: int, on: DataFrame | None = None, where=None) -> tuple[DataFrame, list[float], list[float]]:
    """Zero mean and unit deviation by the statistics of ``on`` (the training rows), or of
    the rows of ``feats`` that meet ``where``."""
    base = feats if on is None else feats.join(on.select("node_id"), "node_id", "left_semi")
    base = base if where is None else base.filter(where)
    row = base.agg(*(F.avg(F.col("h")[j]).alias(f"m{j}") for j in range(width)), *(F.stddev_pop(F.col("h")[j]).alias(f"s{j}") for j in range(width))).first()
    mean = [float(row[f"m{j}"] or 0.0) for j in range(width)]
    dev = [float(row[f"s{j}"] or 0.0) or 1.0 for j in range(width)]
    h = F.array(*((F.col("h")[j] - mean[j]) / dev[j] for j in range(width)))
    return feats.withColumn("h", h), mean, dev


# ------------------------------------------------------------------ labels


def part_region(spark: SparkSession, folder: str, bought: DataFrame | None = None) -> DataFrame:
    """node_id of parts and the region with most distinct buyers (ties: smaller key).

    ``bought``: the edges of ``purchase`` where the caller has them."""
    from prunegraph.operators.edges import purchase

    buyers = (purchase(spark, folder) if bought is None else bought).filter("dst % 4 = 1").select(F.col("dst").alias("node_id"), (F.col("src") / 4).cast("long").alias("c_custkey"))
    c = read(spark, folder, "customer").select("c_custkey", "c_nationkey")
    n = F.broadcast(read(spark, folder, "nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_regionkey"))  # 25 nations
    votes = buyers.join(c, "c_custkey").join(n, "c_nationkey").groupBy("node_id", "n_regionkey").agg(F.count(F.lit(1)).alias("n"))
    return votes.groupBy("node_id").agg(F.max_by("n_regionkey", F.struct(F.col("n"), -F.col("n_regionkey"))).cast("int").alias("label"))


def customer_type(spark: SparkSession, folder: str) -> DataFrame:
    """node_id of customers and the part type they bought most (ties: name order)."""
    from prunegraph.operators.edges import purchase

    bought = purchase(spark, folder).filter("dst % 4 = 0").select(F.col("dst").alias("node_id"), ((F.col("src") - 1) / 4).cast("long").alias("p_partkey"))
    p = read(spark, folder, "part").select("p_partkey", "p_type")
    w = Window.partitionBy("node_id").orderBy(F.desc("n"), "p_type")
    votes = bought.join(p, "p_partkey").groupBy("node_id", "p_type").agg(F.count(F.lit(1)).alias("n"))
    return votes.withColumn("r", F.row_number().over(w)).filter("r = 1").select("node_id", "p_type")


def customer_types_multi(spark: SparkSession, folder: str) -> DataFrame:
    """node_id, p_type, label: whether a type's share of a customer's parts is above its share overall."""
    from prunegraph.operators.edges import purchase

    bought = purchase(spark, folder).filter("dst % 4 = 0").select(F.col("dst").alias("node_id"), ((F.col("src") - 1) / 4).cast("long").alias("p_partkey"))
    pairs = bought.join(read(spark, folder, "part").select("p_partkey", "p_type"), "p_partkey")
    overall = pairs.groupBy("p_type").agg(F.count(F.lit(1)).alias("t")).withColumn("all", F.sum("t").over(Window.partitionBy(F.lit(1))))
    own = pairs.groupBy("node_id").agg(F.count(F.lit(1)).alias("mine"))
    grid = own.crossJoin(F.broadcast(overall))  # a row per part type
    cells = pairs.groupBy("node_id", "p_type").agg(F.count(F.lit(1)).alias("n"))
    full = grid.join(cells, ["node_id", "p_type"], "left")
    return full.select("node_id", "p_type", (F.coalesce("n", F.lit(0)) * F.col("all") > F.col("t") * F.col("mine")).cast("int").alias("label"))
