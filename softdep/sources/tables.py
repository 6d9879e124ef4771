"""Reading tables, and the derived relations of the experiments."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from softdep.relation import Relation

BLANKS = r"[ \t\n\r]+"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_any(spark: SparkSession, path: str, format: str = "parquet", schema: T.StructType | str | None = None, columns: list[str] | None = None, **options: str) -> DataFrame:
    """A table of any batch source: parquet, orc, csv, json, text, jdbc, or table (path is then its name)."""
    if format == "table":
        df = spark.table(path)
    else:
        reader = spark.read.format(format).options(**options)
        reader = reader.schema(schema) if schema is not None else reader
        df = reader.load(path) if format != "jdbc" else reader.load()
    return df.select(*columns) if columns else df


def flattened(df: DataFrame, sep: str = "_") -> DataFrame:
    """Struct columns as one column for each field; other types as they are."""
    out: list[Column] = []
    nested = False
    for f in df.schema.fields:
        if isinstance(f.dataType, T.StructType):
            nested = True
            out += [F.col(f"`{f.name}`.`{x.name}`").alias(f"{f.name}{sep}{x.name}") for x in f.dataType.fields]
        else:
            out.append(F.col(f"`{f.name}`"))
    return flattened(df.select(*out), sep) if nested else df


def hash_sample(df: DataFrame, key: Column, percent: int) -> DataFrame:
    """About percent of the rows, the same ones each time, growing with percent."""
    return df.where(F.pmod(F.xxhash64(key), F.lit(100)) < percent)


def _events(spark: SparkSession, d: str) -> DataFrame:
    k = F.from_json("props", "k int")["k"]
    return load(spark, d, "events").select("user_id", "event_type", "value", k.alias("k"), F.hour("ts").alias("hour"), F.dayofmonth("ts").alias("day"))


def _doc(spark: SparkSession, d: str) -> DataFrame:
    docs = load(spark, d, "documents").select("doc_id", "lang", "source", "n_chars")
    band = F.length(F.bin(F.col("n_chars") + 1)) - 1
    return docs.join(load(spark, d, "labels"), "doc_id", "left").select("doc_id", "lang", "source", "n_chars", "quality", "toxic", band.alias("size_band"))


def _dirty(spark: SparkSession, d: str) -> DataFrame:
    nation = load(spark, d, "nation").join(F.broadcast(load(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 rows by their schema
    c = load(spark, d, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
    market = F.when((F.col("c_custkey") * 7919) % 101 < 4, "OTHER").otherwise(F.col("r_name"))
    rep = F.when((F.col("c_custkey") * 31) % 37 != 0, F.col("c_nationkey") * 10 + F.when(F.col("c_custkey") % 3 == 0, 1).otherwise(0))
    return c.select("c_nationkey", "n_name", "r_name", "c_mktsegment", market.alias("market"), rep.alias("rep"), "c_acctbal")


def _conv(spark: SparkSession, d: str) -> DataFrame:
    text = F.regexp_replace(F.coalesce("text", F.lit("")), f"^{BLANKS}|{BLANKS}$", "")
    words = F.split(text, BLANKS)
    return load(spark, d, "conversations").select("conv_id", "turn", "role", F.when(text == "", 0).otherwise(F.size(words)).alias("n_words"), (F.col("turn") % 2).alias("parity"), F.element_at(words, 1).alias("first_word"))


def _page(spark: SparkSession, d: str) -> DataFrame:
    u = F.col("url")
    return load(spark, d, "pages").select(
        F.regexp_extract(u, "^[a-z]+://([^/?#]*)", 1).alias("host"),
        F.regexp_extract(u, "^[a-z]+://[^/?#]*/([a-z][a-z])(?:[/?#]|$)", 1).alias("url_lang"),
        F.regexp_extract("html", '<html lang="([^"]*)"', 1).alias("html_lang"),
        F.regexp_extract(u, "^([a-z]+)://", 1).alias("scheme"),
        (F.instr(u, "?") > 0).alias("has_query"),
        (F.length(u) - F.length(F.replace(u, F.lit("/"), F.lit("")))).alias("depth"),
        F.floor(F.length("html") / 1024).cast("int").alias("kb"),
    )


def sign_bits(embeddings: DataFrame, bits: int = 20, column: str = "embedding") -> DataFrame:
    """b00, b01, ...: whether the vector's first entries are positive; and label."""
    return embeddings.select(*((F.col(column)[i] > 0).cast("int").alias(f"b{i:02d}") for i in range(bits)), "label")


def present_bits(embeddings: DataFrame, column: str = "embedding") -> DataFrame:
    """109 columns, 1 or NULL: p00 to p63, where an entry of the vector is positive; q00 to q44, where one is beyond 1/8 in
    size."""
    at = lambda i: F.get(column, F.lit(i))
    return embeddings.select(*(F.when(at(i) > 0, 1).alias(f"p{i:02d}") for i in range(64)), *(F.when(F.abs(at(i)) > 0.125, 1).alias(f"q{i:02d}") for i in range(45)))


def _wide(spark: SparkSession, d: str) -> DataFrame:
    nation = load(spark, d, "nation").join(F.broadcast(load(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    li = load(spark, d, "lineitem").join(load(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(load(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    return li.join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).select(
        "l_orderkey", "l_partkey", "l_suppkey", "l_returnflag", "l_linestatus", "l_discount", "o_custkey", "o_orderstatus", "o_orderpriority", "c_nationkey", "c_mktsegment", "n_name", "n_regionkey", "r_name"
    )


DERIVED = {
    "lineitem": lambda s, d: load(s, d, "lineitem"),
    "orders": lambda s, d: load(s, d, "orders"),
    "customer": lambda s, d: load(s, d, "customer"),
    "part": lambda s, d: load(s, d, "part"),
    "events": _events,
    "doc": _doc,
    "dirty": _dirty,
    "conv": _conv,
    "page": _page,
    "bits": lambda s, d: sign_bits(load(s, d, "embeddings")),
    "wide": _wide,
}


def relation(spark: SparkSession, sf_dir: str, name: str, **options: object) -> Relation:
    """One of the experiments' relations by its short name."""
    return Relation.of(DERIVED[name](spark, sf_dir), name=name, **options)
