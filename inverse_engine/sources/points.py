"""Point tables: an id and unrolled double coordinates x0..x{d-1}."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from inverse_engine.functions.geometry import coordinates, total

#: Coordinates that are tested by a sum.
FEW = 8


def dimension(points: DataFrame) -> int:
    return sum(c[0] == "x" and c[1:].isdigit() for c in points.columns)


def make_points(source: DataFrame, id_: Column, coords: Sequence[Column], normalise: bool = True, invalid: str = "drop", check_unique: bool = False) -> DataFrame:
    """Ids and coordinates of a table's rows, scaled to the unit box by their least and greatest values (one job, 2d numbers).

    Rows with a null, NaN or infinite coordinate are dropped, or raise with invalid="raise"."""
    names = coordinates(len(coords))
    # One array column is tested: conditions on many columns would multiply under the optimizer's inference of constraints.
    rows = source.select(id_.cast("long").alias("id"), F.array(*[c.cast("double") for c in coords]).alias("v"))
    if len(names) <= FEW:  # nothing times zero is zero but a number: one sum, which is faster than a lambda
        numbers = total([F.element_at("v", i + 1) * 0.0 for i in range(len(names))]) == 0.0
    else:
        numbers = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    fine = F.col("id").isNotNull() & numbers
    if invalid == "raise" and rows.where(~F.coalesce(fine, F.lit(False))).head(1):
        raise ValueError("a coordinate is null or not finite")
    rows = rows.where(F.coalesce(fine, F.lit(False))).select("id", *[F.get("v", F.lit(i)).alias(n) for i, n in enumerate(names)])
    if check_unique and rows.groupBy("id").count().where("count > 1").head(1):
        raise ValueError("ids repeat")
    if not normalise:
        return rows
    ends = rows.agg(*[f(n).alias(f"{k}{n}") for n in names for k, f in (("lo", F.min), ("hi", F.max))]).first()
    scaled = []
    for n in names:
        lo, hi = ends[f"lo{n}"], ends[f"hi{n}"]
        scaled.append((F.lit(0.0) if lo is None or hi == lo else (F.col(n) - F.lit(lo)) / F.lit(hi - lo)).alias(n))
    return rows.select("id", *scaled)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _days(c: str) -> Column:
    return F.datediff(F.to_date(c), F.lit("1995-01-01").cast("date"))


def _cents(c: str) -> Column:
    """round() of a double goes by its decimal digits, which takes long: the same number, half away from zero, by exact differences."""
    cents = F.col(c) * 100
    size = F.abs(cents)
    half_up = F.floor(size) + (size - F.floor(size) >= 0.5).cast("int")
    return F.when(size < 2.0**52, F.when(cents < 0, -half_up).otherwise(half_up).cast("long")).otherwise(F.round(cents).cast("long"))


def fixture(spark: SparkSession, sf_dir: str, name: str, normalise: bool = True) -> DataFrame:
    """The point tables that the experiments use; sums are of whole cents, so that they do not depend on the order of rows."""
    read = lambda t: read_table(spark, sf_dir, t)
    if name.startswith("line"):
        coords = [F.col("l_quantity"), F.col("l_extendedprice"), _days("l_shipdate"), F.col("l_discount"), F.col("l_tax")][: int(name[4:])]
        return make_points(read("lineitem"), (F.col("l_orderkey") * 8 + F.col("l_linenumber")) * 16777216 + _cents("l_extendedprice"), coords, normalise)
    if name == "orders2":
        return make_points(read("orders"), F.col("o_orderkey"), [F.col("o_totalprice"), _days("o_orderdate")], normalise)
    if name == "part2":
        return make_points(read("part"), F.col("p_partkey"), [F.col("p_size"), F.col("p_retailprice")], normalise)
    if name in ("customer2", "customer3"):
        spent = read("orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.sum(_cents("o_totalprice")).alias("spent"), F.count("*").alias("n"))
        coords = [F.col("c_acctbal"), F.col("spent"), F.col("n")] if name == "customer3" else [F.col("spent"), F.col("n")]
        return make_points(read("customer").join(spent, "c_custkey"), F.col("c_custkey"), coords, normalise)
    if name == "supplier3":
        sold = read("lineitem").groupBy(F.col("l_suppkey").alias("s_suppkey")).agg(F.sum(_cents("l_extendedprice")).alias("sold"), F.count("*").alias("n"))
        return make_points(read("supplier").join(sold, "s_suppkey"), F.col("s_suppkey"), [F.col("s_acctbal"), F.col("sold"), F.col("n")], normalise)
    if name == "users4":
        users = read("events").groupBy("user_id").agg(F.sum(_cents("value")).alias("s"), F.count("*").alias("n"), F.max("value").alias("m")).where(F.col("user_id").isNotNull())
        return make_points(users, F.col("user_id"), [F.col("s"), F.col("n"), F.col("s") / F.col("n"), F.col("m")], normalise)
    if name.startswith("emb"):
        return make_points(read("embeddings"), F.col("vec_id"), [F.get("embedding", F.lit(i)) for i in range(int(name[3:]))], normalise=False)
    if name == "doc3":
        words = F.split(F.coalesce("text", F.lit("")), " ")
        return make_points(read("documents"), F.col("doc_id"), [F.col("n_chars"), F.size(words), F.size(F.array_distinct(words)) / F.size(words)], normalise)
    if name == "conv2":
        turns = read("conversations").groupBy("conv_id").agg(F.count("*").alias("n"), F.sum(F.length("text")).alias("s"))
        return make_points(turns, F.col("conv_id"), [F.col("n"), F.col("s") / F.col("n")], normalise)
    if name == "page2":
        return make_points(read("pages"), F.col("page_id"), [F.length("html"), F.length("html") - F.length(F.translate("html", "<", ""))], normalise)
    raise KeyError(name)


def lattice(spark: SparkSession, d: int, steps: int) -> DataFrame:
    """steps**d points over the unit box, for region-valued queries."""
    cell = [F.floor(F.col("id") / (steps**i)) % steps for i in range(d)]
    return spark.range(steps**d).select("id", *[(c / F.lit(float(steps - 1))).alias(f"x{i}") for i, c in enumerate(cell)])


def synthetic(spark: SparkSession, n: int, d: int, clusters: int = 0, seed: int = 0) -> DataFrame:
    """Uniform points, or points around `clusters` centres, in the unit box."""
    base = spark.range(n)
    if not clusters:
        return base.select("id", *[F.rand(seed + i).alias(f"x{i}") for i in range(d)])
    centre = F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(clusters))
    place = lambda i: F.pmod(F.xxhash64(centre, F.lit(i)), F.lit(1_000_003)) / 1_000_003
    return base.select("id", *[F.least(F.greatest(place(i) + F.randn(seed + i) * 0.05, F.lit(0.0)), F.lit(1.0)).alias(f"x{i}") for i in range(d)])


def write_points(points: DataFrame, path: str, format_: str = "parquet") -> None:
    points.write.format(format_).option("header", "true").save(path)


def read_points(spark: SparkSession, path: str, d: int, format_: str = "parquet") -> DataFrame:
    schema = "id long, " + ", ".join(f"x{i} double" for i in range(d))
    return spark.read.format(format_).schema(schema).option("header", "true").load(path)
