"""Learning tasks over the given tables as units (unit_id, label, features), and the SQL that says the same."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def views(spark: SparkSession, sf_dir: str, names=TABLES) -> SparkSession:
    """Registers the tables as temporary views."""
    for name in names:
        table(spark, sf_dir, name).createOrReplaceTempView(name)
    return spark


class Task:
    """Expressions that both engines read: a label and features, over a table with a unique id."""

    def __init__(self, name: str, table: str, unit_id: str, label: str, features: list[str], gradient: str, unit_id_sql: str | None = None):
        self.name, self.table, self.unit_id, self.label, self.features, self.gradient = name, table, unit_id, label, features, gradient
        #: The id as DuckDB writes it, where that differs.
        self.unit_id_sql = unit_id_sql or unit_id

    @property
    def dim(self) -> int:
        return len(self.features)

    def units(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        return self.over(table(spark, sf_dir, self.table))

    def over(self, rows: DataFrame) -> DataFrame:
        return transform_columns(rows, self.unit_id, self.label, self.features)

    def sql(self) -> str:
        """Units with columns unit_id, label, x0, x1, ..."""
        return f"SELECT {self.unit_id_sql} AS unit_id, CAST({self.label} AS DOUBLE) AS label, " + ", ".join(f"CAST({f} AS DOUBLE) AS x{j}" for j, f in enumerate(self.features)) + f" FROM {self.table}"


def transform_columns(raw: DataFrame, unit_id: str | Column, label: str | Column, features: list) -> DataFrame:
    """Transform: raw rows to dense units by expressions alone, so that pruning reaches the scan."""
    as_col = lambda x: F.expr(x) if isinstance(x, str) else x
    return raw.select(as_col(unit_id).alias("unit_id"), as_col(label).cast("double").alias("label"), F.array(*(as_col(f).cast("double") for f in features)).alias("features"))


_CHARGE = "(l_extendedprice*(1-l_discount)*(1+l_tax))"
_CHARGE_X = ["1.0", "l_extendedprice/105000", "l_discount*10", "l_tax*12.5"]
#: Rows of lineitem have no key (order key and line number repeat): 60 bits of a hash of the columns that tell them apart.
_LINE = "md5(concat_ws(':', l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(l_extendedprice*100) AS BIGINT)))"
_LINE_ID, _LINE_SQL = f"CAST(conv(substr({_LINE}, 1, 15), 16, 10) AS BIGINT)", f"('0x'||substr({_LINE}, 1, 15))::BIGINT"
W1 = Task("charge_regression", "lineitem", _LINE_ID, f"{_CHARGE}/105000", _CHARGE_X, "linear", _LINE_SQL)
W2 = Task("big_charge", "lineitem", _LINE_ID, f"CASE WHEN {_CHARGE} > 52500 THEN 1.0 ELSE -1.0 END", _CHARGE_X, "logistic", _LINE_SQL)
W2_SVM = Task("big_charge_svm", "lineitem", _LINE_ID, W2.label, _CHARGE_X, "hinge", _LINE_SQL)
_K = "CAST(regexp_extract(props, '([0-9]+)', 1) AS DOUBLE)"
W6 = Task("event_heavy", "events", "event_id", f"CASE WHEN value + {_K} > 100 THEN 1.0 ELSE -1.0 END", ["1.0", "value/100", f"{_K}/100"], "hinge")
W7 = Task("part_price", "part", "p_partkey", "p_retailprice/1000", ["1.0", "(p_partkey % 1000)/1000e0"], "linear")
W8 = Task("return_flag", "lineitem", _LINE_ID, "CASE WHEN l_returnflag = 'R' THEN 1.0 ELSE -1.0 END", ["1.0", "(l_quantity-25.5)/14.4", "(l_discount-0.05)/0.03", "(l_tax-0.04)/0.026"], "logistic", _LINE_SQL)
TASKS = {t.name: t for t in (W1, W2, W2_SVM, W6, W7, W8)}


def halfspace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W3: 64 components, labelled by the side of a fixed plane."""
    return side_of_plane(table(spark, sf_dir, "embeddings").withColumn("unit_id", F.col("vec_id")))


def side_of_plane(raw: DataFrame) -> DataFrame:
    """W3's Transform."""
    rows = raw.select("unit_id", F.col("embedding").cast("array<double>").alias("features"))
    plane = F.array(*(F.lit(math.cos(j)) for j in range(64)))
    side = F.aggregate(F.zip_with("features", plane, lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    return rows.select("unit_id", F.when(side > 0, 1.0).otherwise(-1.0).alias("label"), "features")


def embedding_label(spark: SparkSession, sf_dir: str, label: int) -> DataFrame:
    """W10: one label against the rest; a control without signal."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("unit_id"), F.when(F.col("label") == label, 1.0).otherwise(-1.0).alias("label"), F.col("embedding").cast("array<double>").alias("features"))


def order_total(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W9: features from two broadcast-size-free joins; Spark picks their strategy."""
    o, c, n = (table(spark, sf_dir, x) for x in ("orders", "customer", "nation"))
    rows = o.join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey)
    hot = [F.when(F.col("c_mktsegment") == s, 1.0).otherwise(0.0) for s in ("AUTOMOBILE", "BUILDING", "FURNITURE", "MACHINERY")]
    return transform_columns(rows, "o_orderkey", "o_totalprice/5e5", [F.lit(1.0), F.col("c_acctbal") / 10000, *hot])


def spread(rows: DataFrame) -> DataFrame:
    """Rows dealt out over all cores where fewer tasks than that read them, for work that outweighs moving them."""
    cores = rows.sparkSession.sparkContext.defaultParallelism
    return rows.repartition(cores) if rows.rdd.getNumPartitions() < cores else rows


def _hashed(word: Column) -> Column:
    return F.conv(F.substring(F.md5(word), 1, 8), 16, 10).cast("long")


def doc_words(spark: SparkSession, sf_dir: str, dim: int = 1024) -> DataFrame:
    """(unit_id, bucket) of a hashed bag of words, each bucket once."""
    words = spread(table(spark, sf_dir, "documents").select("doc_id", "text")).select(F.col("doc_id").alias("unit_id"), F.explode(F.array_distinct(F.split(F.lower("text"), "[ \n\t]+"))).alias("w"))
    return words.where("w <> ''").select("unit_id", (_hashed(F.col("w")) % dim).cast("int").alias("bucket")).distinct()


def doc_hashes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(unit_id, hashes) of the words of ``doc_words``, hashed where a text is read: a row a text is shuffled, not one a word."""
    texts = spread(table(spark, sf_dir, "documents").select(F.col("doc_id").alias("unit_id"), "text"))
    words = F.filter(F.array_distinct(F.split(F.lower("text"), "[ \n\t]+")), lambda w: w != "")
    own = texts.select("unit_id", F.transform(words, _hashed).alias("own")).groupBy("unit_id").agg(F.collect_list("own").alias("own"))
    return own.select("unit_id", F.flatten("own").alias("hashes")).where(F.size("hashes") > 0)


def doc_language(spark: SparkSession, sf_dir: str, dim: int = 1024, hashes: DataFrame | None = None) -> DataFrame:
    """W4: sparse units (unit_id, label, dim, idx, val) of unit length; the label tells English. ``hashes`` are those of
    ``doc_hashes`` where a caller holds them, for several dimensions."""
    hashes = doc_hashes(spark, sf_dir) if hashes is None else hashes
    bags = hashes.select("unit_id", F.array_sort(F.array_distinct(F.transform("hashes", lambda h: (h % dim).cast("int")))).alias("idx"))
    labels = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("unit_id"), F.when(F.col("lang") == "en", 1.0).otherwise(-1.0).alias("label"))
    return labels.join(bags, "unit_id").select("unit_id", "label", F.lit(dim).alias("dim"), "idx", F.transform("idx", lambda _: 1 / F.sqrt(F.size("idx"))).alias("val"))


def doc_quality(spark: SparkSession, sf_dir: str, dim: int = 1024) -> DataFrame:
    """W5: as W4 with the labels table's quality, and the log of the length as one more feature."""
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("unit_id"), "n_chars")
    labels = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("unit_id"), (2.0 * F.col("quality") - 1).alias("y"))
    words = doc_language(spark, sf_dir, dim).drop("label")
    return words.join(labels, "unit_id").join(docs, "unit_id").select("unit_id", F.col("y").alias("label"), F.lit(dim + 1).alias("dim"), F.array_append("idx", F.lit(dim)).alias("idx"), F.array_append("val", F.log1p("n_chars") / 10).alias("val"))


UNIT = T.StructType([T.StructField("unit_id", T.LongType()), T.StructField("label", T.DoubleType()), T.StructField("features", T.ArrayType(T.DoubleType()))])


def numbered_lines(spark: SparkSession, path: str) -> DataFrame:
    """(unit_id, value): lines named by the split they are read in and their place there, so that equal lines are units of
    their own. Ids are the same in every scan of the same files with the same split size."""
    return spark.read.text(path).select(F.monotonically_increasing_id().alias("unit_id"), "value")


def read_csv_units(spark: SparkSession, path: str, label: int = 0) -> DataFrame:
    """Comma-separated lines; the first column is the label by default. Lazy: lines become units by expressions."""
    cells = F.transform(F.split(F.trim("value"), ","), lambda x: x.cast("double"))
    return numbered_lines(spark, path).select("unit_id", F.element_at(cells, label + 1).alias("label"), F.concat(F.slice(cells, 1, label), F.slice(cells, label + 2, 1 << 20)).alias("features"))


def read_libsvm_units(spark: SparkSession, path: str, dim: int | None = None) -> DataFrame:
    """Lines ``label i:v i:v``, indices from 1, as sparse units."""
    parts = F.split(F.trim("value"), "\\s+")
    rows = numbered_lines(spark, path).where("trim(value) <> ''").select("unit_id", F.element_at(parts, 1).cast("double").alias("label"), F.slice(parts, 2, 1 << 24).alias("cells"))
    rows = rows.select("unit_id", "label", F.transform("cells", lambda c: F.split(c, ":")[0].cast("int") - 1).alias("idx"), F.transform("cells", lambda c: F.split(c, ":")[1].cast("double")).alias("val"))
    if dim is None:
        dim = (rows.agg(F.max(F.array_max("idx"))).first()[0] or 0) + 1
    return rows.select("unit_id", "label", F.lit(dim).alias("dim"), "idx", "val")


def densify(sparse: DataFrame) -> DataFrame:
    """Sparse units with all their components; for dimensions that a row can hold."""
    # a map would be made anew for each component, as what stands in a lambda is evaluated there
    return sparse.select("unit_id", "label", F.transform(F.sequence(F.lit(0), F.col("dim") - 1), lambda j: F.coalesce(F.get("val", F.array_position("idx", j).cast("int") - 1), F.lit(0.0))).alias("features"))
