"""Answers from the given tables, and readers and writers of answers and rankings.

All response sets have user_id long, item_id string, option_id string.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

RESPONSES = T.StructType([T.StructField("user_id", T.LongType()), T.StructField("item_id", T.StringType()), T.StructField("option_id", T.StringType())])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def latest(df: DataFrame, order: list[str]) -> DataFrame:
    """One answer for each user and item: the last by a total order; the window keeps one row a
    group before the shuffle."""
    last = Window.partitionBy("user_id", "item_id").orderBy(*[F.desc(c) for c in order])
    return df.withColumn("_n", F.row_number().over(last)).where("_n = 1").select("user_id", "item_id", "option_id")


def answers(user: str, item, option, df: DataFrame, *order: str) -> DataFrame:
    item = F.col(item) if isinstance(item, str) else item
    option = F.col(option) if isinstance(option, str) else option
    return df.select(F.col(user).cast("long").alias("user_id"), item.cast("string").alias("item_id"), option.cast("string").alias("option_id"), *order)


def supplier_brand(spark: SparkSession, d: str) -> DataFrame:
    line = table(spark, d, "lineitem").join(table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand"), "l_partkey")
    return latest(answers("l_suppkey", "p_brand", "l_returnflag", line, "l_shipdate", "l_orderkey", "l_linenumber"), ["l_shipdate", "l_orderkey", "l_linenumber", "option_id"])


def supplier_part(spark: SparkSession, d: str) -> DataFrame:
    return latest(answers("l_suppkey", "l_partkey", "l_returnflag", table(spark, d, "lineitem"), "l_shipdate", "l_orderkey", "l_linenumber"), ["l_shipdate", "l_orderkey", "l_linenumber", "option_id"])


def customer_quarter(spark: SparkSession, d: str) -> DataFrame:
    quarter = F.concat(F.year("o_orderdate").cast("string"), F.lit("Q"), F.quarter("o_orderdate").cast("string"))
    return latest(answers("o_custkey", quarter, "o_orderpriority", table(spark, d, "orders"), "o_orderdate", "o_orderkey"), ["o_orderdate", "o_orderkey"])


def user_day(spark: SparkSession, d: str) -> DataFrame:
    return latest(answers("user_id", F.to_date("ts"), "event_type", table(spark, d, "events"), "ts", "event_id"), ["ts", "event_id"])


def vector_dimension(spark: SparkSession, d: str) -> DataFrame:
    """The third of its dimension that each coordinate falls in; equal values by id."""
    flat = table(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("dim", "x"))
    third = F.ntile(3).over(Window.partitionBy("dim").orderBy("x", "vec_id"))
    return flat.select(F.col("vec_id").cast("long").alias("user_id"), F.col("dim").cast("string").alias("item_id"), third.cast("string").alias("option_id"))


#: feature -> (numerator, denominator or None, cut points as integers; shares in thousandths)
def _doc_counts(text):
    """What is rare in texts is found and taken off, what is common is kept by runs: few matches either way."""
    whole = F.length(F.regexp_replace(text, "(?!)", "")).cast("long")  # as decoded, like the others
    kept = lambda rest: F.length(F.regexp_replace(text, f"{rest}+", "")).cast("long")
    off = lambda own: whole - kept(own)
    return {
        "chars": F.length(text).cast("long"), "letters": kept("[^a-zA-Z]"), "digits": off("[0-9]"), "capitals": off("[A-Z]"), "lines": off("\n") + 1,
        "marks": off("[.,;:!?]"), "symbols": off("[#*$%&|<>]"), "blanks": off(" "), "wide": kept("[\\x00-\\x7F]"),
    }


FEATURES = (("chars", None, (500, 1500, 4000)), ("letters", "chars", (700, 780, 820)), ("digits", "chars", (1, 5, 20)), ("capitals", "chars", (10, 20, 60)), ("lines", None, (3, 8, 20)), ("marks", "chars", (10, 20, 40)), ("symbols", "chars", (1, 10, 50)), ("blanks", "chars", (120, 150, 180)), ("wide", "chars", (1, 20, 60)))


def document_features(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents")
    text = F.coalesce("text", F.lit(""))
    counted = docs.select("doc_id", F.coalesce("lang", F.lit("none")).alias("lang"), *[c.alias(n) for n, c in _doc_counts(text).items()])
    bins = []
    for name, over, cuts in FEATURES:
        passed = [(F.col(name) >= c) if over is None else (1000 * F.col(name) >= c * F.col(over)) for c in cuts]
        bins.append(F.struct(F.lit(name).alias("item_id"), sum((p.cast("int") for p in passed), F.lit(0)).cast("string").alias("option_id")))
    bins.append(F.struct(F.lit("lang").alias("item_id"), F.col("lang").alias("option_id")))
    return counted.select(F.col("doc_id").cast("long").alias("user_id"), F.explode(F.array(*bins)).alias("b")).select("user_id", "b.item_id", "b.option_id")


def conversation_turn(spark: SparkSession, d: str) -> DataFrame:
    option = F.concat("role", F.lit(":"), F.floor(F.length("text") / 100).cast("string"))
    return answers("conv_id", "turn", option, table(spark, d, "conversations"))


SETS = {"R1": supplier_brand, "R2": supplier_part, "R3": customer_quarter, "R4": user_day, "R5": vector_dimension, "R6": document_features, "R7": conversation_turn}


def rset(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return SETS[name](spark, sf_dir)


def passage_items(spark: SparkSession, d: str, most_bytes: int = 64 << 20) -> DataFrame:
    """user_id (doc_id), item_id (benchmark item): documents that hold a benchmark passage.

    All passages are found in one run of an automaton over each text; the passages are sent out
    below a checked size, and matched by blocks of items beyond it."""
    import pyarrow as pa

    passages = table(spark, d, "benchmark").where("length(text) > 0").select("item_id", "text")
    size = passages.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    blocks = max(1, -(-int(size) // most_bytes))
    docs = table(spark, d, "documents").where("text is not null").select("doc_id", "text")
    out = None
    for b in range(blocks):
        held = [(r["item_id"], r["text"]) for r in passages.where(F.pmod(F.xxhash64("item_id"), F.lit(blocks)) == b).collect()]
        sent = spark.sparkContext.broadcast(held)

        def run(batches, sent=sent):
            import ahocorasick

            automaton, by_text = ahocorasick.Automaton(), {}
            for item, text in sent.value:
                by_text.setdefault(text, []).append(item)
            for text, items in by_text.items():
                automaton.add_word(text, items)
            automaton.make_automaton()
            for batch in batches:
                rows = [(doc, item) for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()) for item in sorted({i for _, items in automaton.iter(text) for i in items})]
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64())], ["user_id", "item_id"])

        part = docs.mapInArrow(run, "user_id long, item_id long") if held else spark.createDataFrame([], "user_id long, item_id long")
        out = part if out is None else out.unionByName(part)
    return out


def page_features(spark: SparkSession, d: str) -> DataFrame:
    """Answers of pages: how often a tag occurs, up to three."""
    pages = table(spark, d, "pages").select("page_id", F.coalesce("html", F.lit("")).alias("html"))
    tags = F.array(*[F.struct(F.lit(t).alias("item_id"), F.least(F.lit(3), F.regexp_count("html", F.lit(f"<{t}[ >]"))).cast("string").alias("option_id")) for t in ("p", "a", "div", "li", "script")])
    return pages.select(F.col("page_id").cast("long").alias("user_id"), F.explode(tags).alias("t")).select("user_id", "t.item_id", "t.option_id")


def read_responses(spark: SparkSession, path: str, fmt: str = "parquet", mapping: dict[str, str] | None = None, schema: T.StructType | str | None = None, **options) -> DataFrame:
    """Answers from Parquet, ORC, CSV, JSON or text; mapping: our column -> theirs."""
    reader = spark.read.format(fmt).options(**options)
    if fmt in ("csv", "json"):
        reader = reader.schema(schema or RESPONSES)
    elif schema is not None:
        reader = reader.schema(schema)
    df = reader.load(path)
    if fmt == "text":  # user, item and option parted by tabs
        parts = F.split("value", "\t")
        df = df.select(*[F.get(parts, i).alias(c) for i, c in enumerate(("user_id", "item_id", "option_id"))])
    mapping = mapping or {}
    return df.select(F.col(mapping.get("user_id", "user_id")).cast("long").alias("user_id"), F.col(mapping.get("item_id", "item_id")).cast("string").alias("item_id"), F.col(mapping.get("option_id", "option_id")).cast("string").alias("option_id"))


def from_table(spark: SparkSession, name: str) -> DataFrame:
    return spark.table(name)


def from_sql(spark: SparkSession, query: str) -> DataFrame:
    return spark.sql(query)


def write_ranking(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite", partition_by: list[str] | None = None) -> None:
    writer = df.write.format(fmt).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def write_bucketed(responses: DataFrame, name: str, buckets: int, mode: str = "overwrite") -> None:
    """A table bucketed and sorted by user: later rounds join and aggregate by user without a shuffle."""
    responses.write.mode(mode).bucketBy(buckets, "user_id").sortBy("user_id", "item_id").saveAsTable(name)
