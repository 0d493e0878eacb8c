"""The data model: one row for each answer (user_id, item_id, option_id), unique by user and item.

Options belong to their item: equal option ids of two items are different options.  An item that a
user did not answer has no row.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

OPTION = ["item_id", "option_id"]


class SizeGuardError(ValueError):
    """A method that needs a quadratic object was given too large an input; the text names another."""


@dataclass(frozen=True)
class Opts:
    max_iter: int = 1000
    tol: float = 1e-5
    seed: int = 42
    check_every: int = 1
    score_digits: int = 9
    path: str = "auto"  # gram: option space on the driver; sql: joins; arrow: packed rows
    max_options: int = 4_000
    max_users: int = 5_000
    rounds: int | None = None  # a fixed number of rounds instead of a tolerance


def validate(responses: DataFrame) -> dict[str, int]:
    """Counts of what the model forbids: repeated (user, item) pairs and nulls."""
    nulls = F.sum((F.col("user_id").isNull() | F.col("item_id").isNull() | F.col("option_id").isNull()).cast("long"))
    repeated = responses.groupBy("user_id", "item_id").count().where("count > 1").count()
    return {"repeated_pairs": repeated, "nulls": responses.agg(F.coalesce(nulls, F.lit(0)).alias("n")).first()["n"]}


def answered(responses: DataFrame) -> DataFrame:
    """Without unanswered items: a null option is no answer."""
    return responses.where("user_id is not null and item_id is not null and option_id is not null")


def one_hot(responses: DataFrame) -> DataFrame:
    """The binary matrix in coordinate form: user, option number, 1."""
    return responses.join(option_dictionary(responses), OPTION).select("user_id", "option_ix", F.lit(1).alias("value"))


def option_dictionary(responses: DataFrame) -> DataFrame:
    """item_id, option_id, option_ix: dense numbers in item and option order, by range and offset."""
    from .operators.rank import global_rank

    return global_rank(responses.select(*OPTION).distinct(), OPTION, "option_ix").withColumn("option_ix", F.col("option_ix") - 1)


def pack(responses: DataFrame) -> DataFrame:
    """user_id and its sorted (item, option) entries in one array."""
    return responses.groupBy("user_id").agg(F.sort_array(F.collect_list(F.struct("item_id", "option_id"))).alias("choices"))


def unpack(packed: DataFrame) -> DataFrame:
    return packed.select("user_id", F.explode("choices").alias("c")).select("user_id", "c.item_id", "c.option_id")


def to_wide(responses: DataFrame, items: list[str] | None = None, most: int = 10_000) -> DataFrame:
    """users x items with options as entries."""
    if items is None:
        items = [r[0] for r in responses.select("item_id").distinct().limit(most + 1).collect()]
        if len(items) > most:
            raise SizeGuardError(f"more than {most} items: use pack")
    return responses.groupBy("user_id").pivot("item_id", sorted(items)).agg(F.first("option_id"))


def from_wide(df: DataFrame, user: str, items: list[str]) -> DataFrame:
    """Entries that are not null, as answers."""
    return df.select(F.col(user).alias("user_id"), *[F.col(c).cast("string").alias(c) for c in items]).unpivot("user_id", items, "item_id", "option_id").where("option_id is not null")


def from_one_hot(df: DataFrame, options_per_item: int) -> DataFrame:
    """(user_id, column, value) of a one-hot matrix with the same number of columns for each item."""
    return df.where("value = 1").select("user_id", F.floor(F.col("column") / options_per_item).cast("long").alias("item_id"), (F.col("column") % options_per_item).cast("int").alias("option_id"))


def response_stats(responses: DataFrame) -> DataFrame:
    """One row: users, items, options, answers, largest number of options of an item, density."""
    per_option = responses.groupBy(*OPTION).agg(F.count("*").alias("n"))
    per_item = per_option.groupBy("item_id").agg(F.count("*").alias("k"), F.sum("n").alias("n"))
    items = per_item.agg(F.count("*").alias("n_items"), F.sum("k").alias("n_options"), F.sum("n").alias("n_answers"), F.max("k").alias("max_options"))
    users = responses.select("user_id").distinct().agg(F.count("*").alias("n_users"))
    return items.crossJoin(users).select("n_users", "n_items", "n_options", "n_answers", "max_options", F.round(F.col("n_answers") / (F.col("n_users") * F.col("n_items")), 6).alias("density"))


def filter_min_answers(responses: DataFrame, min_user: int, min_item: int, most_rounds: int = 20) -> DataFrame:
    """Users and items with enough answers, again until nothing changes."""
    from .plans.storage import written

    before = responses.count()
    for _ in range(most_rounds):
        users = responses.groupBy("user_id").count().where(F.col("count") >= min_user).select("user_id")
        responses = responses.join(users, "user_id", "left_semi")
        items = responses.groupBy("item_id").count().where(F.col("count") >= min_item).select("item_id")
        responses = written(responses.join(items, "item_id", "left_semi"), "filtered")
        now = responses.count()
        if now == before:
            break
        before = now
    return responses


def drop_unanimous(responses: DataFrame) -> DataFrame:
    """Without items of which everybody picked the same option: they order nobody."""
    split = responses.groupBy("item_id").agg(F.min("option_id").alias("x"), F.max("option_id").alias("y")).where("x <> y").select("item_id")
    return responses.join(split, "item_id", "left_semi")


def collapse_users(responses: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(answers of one user for each distinct row of answers, user_id -> that user and multiplicity)."""
    rows = pack(responses).withColumn("key", F.sha2(F.to_json(F.struct("choices")), 256))
    first = rows.groupBy("key").agg(F.min("user_id").alias("kept"), F.count("*").alias("multiplicity"))
    members = rows.select("user_id", "key").join(first, "key").select("user_id", "kept", "multiplicity")
    return responses.join(first.select(F.col("kept").alias("user_id")), "user_id", "left_semi"), members


def sample_keys(responses: DataFrame, column: str, share: float, seed: int = 42) -> DataFrame:
    """Answers of a share of the users or items, chosen by hash: the same ones on every run."""
    return responses.where(F.pmod(F.xxhash64(F.col(column), F.lit(seed)), F.lit(1_000_000)) < int(share * 1_000_000))
