"""The experiment workloads on the given tables.

Gaussian samples are eight times the embedding coordinates, Gamma samples of shape one half are half of
their squares, the uniform sample is the rescaled order price.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks.operators.prefix import cumulative
from driftks.operators.samples import Sample
from driftks.sources import load

#: Number of quantiles and rank error of the convergence study.
CONVERGENCE = [(11, 0.1), (21, 0.1), (51, 0.1), (11, 0.01), (21, 0.01), (51, 0.01), (101, 0.001), (201, 0.001), (501, 0.001)]
#: Level and precision of the distance in the five test experiments.
SETTINGS = {"w1": (0.05, 0.000399), "w2": (0.05, 0.000399), "w3": (0.05, 0.000399), "w4": (0.20, 0.00077), "w5": (0.20, 0.00077)}
#: Target precision in the comparison with the direct-sketch test.
PRECISION = {"w1": 0.05, "w2": 0.01, "w3": 0.001, "w4": 0.05, "w5": 0.002}


def gauss(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``vec_id``, ``dim`` and ``z``, a standard normal value."""
    e = load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("dim", "c"))
    return e.select("vec_id", "dim", (F.lit(8.0) * F.col("c").cast("double")).alias("z"))


def uniform_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").select("o_orderkey", ((F.col("o_totalprice") - 1000.0) / 499000.0).alias("u"))


def gauss_pair(spark: SparkSession, sf_dir: str, change: Column | None = None, only: Column | None = None) -> tuple[Sample, Sample]:
    g = gauss(spark, sf_dir) if only is None else gauss(spark, sf_dir).where(only)
    return Sample(g, "z", "vec_id % 2 = 0"), Sample(g, F.col("z") if change is None else change, "vec_id % 2 = 1")


def gamma_pair(spark: SparkSession, sf_dir: str, uniform: bool, only: Column | None = None) -> tuple[Sample, Sample]:
    g = gauss(spark, sf_dir) if only is None else gauss(spark, sf_dir).where(only)
    value = F.col("z") * F.col("z") / 2.0
    if uniform:
        u = uniform_price(spark, sf_dir).where("o_orderkey % 12 = 0")
        return Sample(g, value), Sample(u, "u")
    return Sample(g, value, "vec_id % 13 <> 0"), Sample(g, value, "vec_id % 13 = 0")


def pair(name: str, spark: SparkSession, sf_dir: str, only: Column | None = None) -> tuple[Sample, Sample]:
    """The samples of a named workload."""
    t = lambda table: load(spark, sf_dir, table)
    if name == "w1":
        return gauss_pair(spark, sf_dir, F.col("z") + 1.0, only)
    if name == "w2":
        return gauss_pair(spark, sf_dir, F.col("z") * 2.0**0.5, only)
    if name == "w3":
        return gauss_pair(spark, sf_dir, None, only)
    if name in ("w4", "w5"):
        return gamma_pair(spark, sf_dir, name == "w4", only)
    if name in ("price", "quantity"):
        column = {"price": "l_extendedprice", "quantity": "l_quantity"}[name]
        return tuple(Sample(t("lineitem"), column, f"l_returnflag = '{f}'") for f in "RN")
    if name == "discount_tax":
        return Sample(t("lineitem"), "l_discount"), Sample(t("lineitem"), "l_tax")
    if name == "events_type":
        return tuple(Sample(t("events"), "value", f"event_type = '{k}'") for k in ("click", "purchase"))
    if name == "events_week":
        return Sample(t("events"), "value", "ts < timestamp_ntz'2024-01-22'"), Sample(t("events"), "value", "ts >= timestamp_ntz'2024-01-22' and ts < timestamp_ntz'2024-01-29'")
    if name == "acctbal":
        return Sample(t("customer"), "c_acctbal"), Sample(t("supplier"), "s_acctbal")
    if name == "totalprice":
        return tuple(Sample(t("orders"), "o_totalprice", f"o_orderstatus = '{s}'") for s in "FO")
    if name == "nchars":
        d = t("documents").select("doc_id", "n_chars").join(t("labels").select("doc_id", "quality"), "doc_id")
        return Sample(d, "n_chars", "quality = 1"), Sample(d, "n_chars", "quality = 0")
    if name == "nchars_lang":
        return tuple(Sample(t("documents"), "n_chars", f"lang = '{k}'") for k in ("en", "de"))
    if name == "textlen":
        return tuple(Sample(t("conversations"), F.char_length("text"), f"role = '{r}'") for r in ("user", "assistant"))
    if name == "retailprice":
        return Sample(t("part"), "p_retailprice", "p_size <= 25"), Sample(t("part"), "p_retailprice", "p_size > 25")
    raise KeyError(name)


def normal_slices(spark: SparkSession, sf_dir: str, k: int = 20) -> DataFrame:
    """``sample`` (0 to k-1) and ``value``: ``k`` disjoint normal samples, three embedding dimensions each."""
    g = gauss(spark, sf_dir).where(F.col("dim") < 3 * k)
    return g.select(F.floor(F.col("dim") / 3).cast("int").alias("sample"), F.col("z").alias("value"))


def replications(name: str, spark: SparkSession, sf_dir: str, k: int = 20) -> DataFrame:
    """``rep``, ``is_x`` and ``value``: ``k`` disjoint parts of a workload's samples, by plain modulo of the vector id (a
    sample without one is in all parts)."""
    e = gauss(spark, sf_dir).withColumn("rep", F.pmod(F.floor(F.col("vec_id") / 2), F.lit(k)).cast("int"))
    z, even = F.col("z"), F.col("vec_id") % 2 == 0
    if name == "w4":
        every = uniform_price(spark, sf_dir).where("o_orderkey % 12 = 0").select(F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("rep"), F.lit(False).alias("is_x"), F.col("u").alias("value"))
        return e.select("rep", F.lit(True).alias("is_x"), (z * z / 2.0).alias("value")).unionByName(every)
    if name == "w5":
        return e.select("rep", (F.col("vec_id") % 13 != 0).alias("is_x"), (z * z / 2.0).alias("value"))
    change = {"w1": z + 1.0, "w2": z * 2.0**0.5, "w3": z}[name]
    return e.select("rep", even.alias("is_x"), F.when(even, z).otherwise(change).alias("value"))


#: Sizes of the samples in the replicated experiments, and in the comparison with the direct-sketch test.
SIZES = {"w1": (10_000, 10_000), "w2": (10_000, 10_000), "w3": (10_000, 10_000), "w4": (84_000, 7_000), "w5": (84_000, 7_000)}
THIRD = {"w1": 10_000, "w2": 10_000, "w3": 100_000, "w4": 84_000, "w5": 84_000}


def drawn(stream: str, number: Column) -> Column:
    """A uniform draw from a hash of the row number: the same on every cluster, and one that SQL repeats."""
    digits = F.substring(F.md5(F.concat(F.lit(f"{stream}:"), number.cast("string")).cast("binary")), 1, 13)
    return (F.conv(digits, 16, 10).cast("long").cast("double") + 0.5) / 4503599627370496.0


def normal_draw(stream: str, number: Column) -> Column:
    return F.sqrt(-2.0 * F.log(drawn(f"{stream}a", number))) * F.cos(F.lit(6.283185307179586) * drawn(f"{stream}b", number))


def full_size(name: str, spark: SparkSession, reps: int = 20, sizes: tuple[int, int] | None = None, stream: str = "") -> DataFrame:
    """``rep``, ``is_x`` and ``value``: a workload at the sizes of its experiment, ``reps`` independent pairs of samples."""
    n, m = sizes or SIZES[name]
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    rows = spark.range(0, reps * (n + m), 1, parts).select(F.floor(F.col("id") / (n + m)).cast("int").alias("rep"), (F.col("id") % (n + m) < n).alias("is_x"), "id")
    z, u = normal_draw(f"{stream}{name}", F.col("id")), drawn(f"{stream}{name}a", F.col("id"))
    x = z * z / 2.0 if name in ("w4", "w5") else z
    y = {"w1": z + 1.0, "w2": z * 2.0**0.5, "w3": z, "w4": u, "w5": z * z / 2.0}[name]
    return rows.select("rep", "is_x", F.when(F.col("is_x"), x).otherwise(y).alias("value"))


def numbered(df: DataFrame, order: str) -> DataFrame:
    """Add ``no``, the place of each row by ``order``, from 0, and ``rows``, their number; no task sees all rows."""
    out = cumulative(df.withColumn("__one", F.lit(1)), [], order, ["__one"])
    return out.select(*df.columns, (F.col("__one_upto") - 1).alias("no"), F.col("__one_all").alias("rows"))


def resampled(name: str, spark: SparkSession, sf_dir: str, reps: int = 20, sizes: tuple[int, int] | None = None, stream: str = "") -> DataFrame:
    """``rep``, ``is_x`` and ``value``: ``reps`` pairs of samples of a workload at the sizes of its experiment, drawn with replacement from the given tables.

    A draw picks one of the numbered values of its table by a hash of its own number: the same on every cluster, and repeated by SQL.
    """
    n, m = sizes or SIZES[name]
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    draws = spark.range(0, reps * (n + m), 1, parts).select(F.floor(F.col("id") / (n + m)).cast("int").alias("rep"), (F.col("id") % (n + m) < n).alias("is_x"), drawn(f"{stream}{name}a", F.col("id")).alias("u"))

    def picked(draws: DataFrame, rows: DataFrame) -> DataFrame:
        table = numbered(rows, "key")
        total = F.broadcast(table.select(F.col("rows").alias("__rows")).limit(1))
        return draws.crossJoin(total).withColumn("__no", F.floor(F.col("u") * F.col("__rows"))).join(table, F.col("__no") == F.col("no"))

    normal = gauss(spark, sf_dir).where(F.col("z").isNotNull()).select(F.struct("vec_id", "dim").alias("key"), "z")
    z, is_x = F.col("z"), F.col("is_x")
    half = z * z / 2.0
    if name == "w4":
        prices = uniform_price(spark, sf_dir).where(F.col("u").isNotNull()).select(F.col("o_orderkey").alias("key"), F.col("u").alias("value"))
        return picked(draws.where(is_x), normal).select("rep", "is_x", half.alias("value")).unionByName(picked(draws.where(~is_x), prices).select("rep", "is_x", "value"))
    x, y = {"w1": (z, z + 1.0), "w2": (z, z * 2.0**0.5), "w3": (z, z), "w5": (half, half)}[name]
    return picked(draws, normal).select("rep", "is_x", F.when(is_x, x).otherwise(y).alias("value"))


def sides(rows: DataFrame) -> tuple[Sample, Sample]:
    """The two samples of a table with ``is_x`` and ``value``."""
    return Sample(rows, "value", "is_x"), Sample(rows, "value", "not is_x")
