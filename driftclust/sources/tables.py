"""Input tables: batch reads, the event stream, and the stand-in data sets.

A data set is a DataFrame of points: chunk_id, obj_id, x (array of doubles,
scaled to [0, 1]), label.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import features

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def table(spark: SparkSession, sf_dir: str, name: str, fmt: str = "parquet") -> DataFrame:
    return spark.read.format(fmt).load(f"{sf_dir}/{name}.{fmt}")


def read_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The event table as a stream with event time; explicit schema."""
    raw = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def _text(c: str) -> dict[str, Column]:
    t = F.coalesce(F.col(c), F.lit(""))
    n = F.greatest(F.length(t), F.lit(1))
    words = F.regexp_count(t, F.lit("[^ \\n\\t]+"))
    return {
        "length": F.length(t).cast("double"),
        "words": words.cast("double"),
        "word_len": F.length(t) / F.greatest(words, F.lit(1)),
        "lines": (F.regexp_count(t, F.lit("\\n")) + 1).cast("double"),
        "digits": F.regexp_count(t, F.lit("[0-9]")) / n,
        "punct": F.regexp_count(t, F.lit("[.,;:!?]")) / n,
        "upper": F.regexp_count(t, F.lit("[A-Z]")) / n,
        "marks": F.regexp_count(t, F.lit("[#$%&*|]")) / n,
        "spaces": F.regexp_count(t, F.lit(" ")) / n,
        "wide": (F.octet_length(t) - F.length(t)) / n,
    }


def _code(*columns) -> Column:
    """A small integer for a class."""
    return F.pmod(F.xxhash64(*columns), F.lit(1_000_003)).cast("int")


def points(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A stand-in data set by its short name, scaled to [0, 1]; chunk_id is 0."""
    t = lambda n: table(spark, sf_dir, n)
    if name in ("ga", "id", "drift", "dense", "grid"):
        from ..operators.planted import mixture

        return mixture(spark, sf_dir, name)
    if name in ("hs", "hf", "ce"):
        f = _text("text")
        picked = {"hs": ("length", "words", "word_len"), "ce": ("length", "words", "lines", "digits", "punct", "upper"), "hf": (*f, )}[name]
        label = {"hs": F.col("quality"), "hf": F.col("toxic"), "ce": F.col("quality") * 2 + F.col("toxic")}[name]
        df = t("documents").join(t("labels"), "doc_id").select(F.col("doc_id").alias("obj_id"), F.array(*[f[c].cast("double") for c in picked]).alias("x"), label.cast("int").alias("label"))
    elif name == "lm":
        df = t("events").select(F.col("event_id").alias("obj_id"), F.array(F.col("value"), F.hour("ts").cast("double"), F.get_json_object("props", "$.k").cast("double")).alias("x"), _code("event_type").alias("label"))
    elif name in ("ra", "se"):
        cols = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber", "l_suppkey"]
        rows = t("lineitem")
        df = rows.select(F.xxhash64(*rows.columns).alias("obj_id"), F.array(*[F.col(c).cast("double") for c in cols], F.datediff("l_shipdate", F.lit("1995-01-01")).cast("double")).alias("x"), _code("l_linestatus" if name == "ra" else "l_returnflag").alias("label"))
    elif name == "ab":
        rows = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
        lag = F.datediff("l_shipdate", "o_orderdate")
        rows = rows.withColumn("obj_id", F.xxhash64(*t("lineitem").columns))
        df = rows.select("obj_id", F.array(*[F.col(c).cast("double") for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "o_totalprice", "p_size", "p_retailprice")], lag.cast("double")).alias("x"), _code("l_linenumber", "l_returnflag", "l_linestatus").alias("label"))
    elif name == "pb":
        o = t("orders").groupBy("o_custkey").agg(F.count("*").alias("n"), *[getattr(F, f)("o_totalprice").alias(f) for f in ("sum", "avg", "min", "max")], F.coalesce(F.stddev("o_totalprice"), F.lit(0.0)).alias("dev"), F.datediff(F.min("o_orderdate"), F.lit("1995-01-01")).alias("first"), F.datediff(F.max("o_orderdate"), F.lit("1995-01-01")).alias("last"), F.count_distinct("o_orderpriority").alias("kinds"))
        df = t("customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left").select(F.col("c_custkey").alias("obj_id"), F.array(*[F.coalesce(F.col(c).cast("double"), F.lit(0.0)) for c in ("c_acctbal", "n", "sum", "avg", "min", "max", "dev", "first", "last", "kinds")]).alias("x"), _code("c_mktsegment").alias("label"))
    elif name == "wc":
        f = _text("text")
        df = t("conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("obj_id"), F.array(F.col("turn").cast("double"), *[f[c].cast("double") for c in ("length", "words", "word_len", "digits", "punct", "lines")]).alias("x"), _code("role").alias("label"))
    elif name == "hd":
        df = t("embeddings").select(F.col("vec_id").alias("obj_id"), F.col("embedding").cast("array<double>").alias("x"), "label")
    else:
        raise ValueError(f"no data set is called {name}")
    return features.minmax(df.select(F.lit(0).cast("long").alias("chunk_id"), "obj_id", "x", "label"))


#: Short name -> number of true clusters.
SETS = {"ga": 4, "id": 5, "ab": 28, "ce": 4, "hs": 2, "hf": 2, "lm": 5, "pb": 5, "ra": 2, "se": 3, "wc": 3}
