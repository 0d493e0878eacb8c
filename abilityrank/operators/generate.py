"""Generated answers with known abilities.  Every draw is an md5 of ids and a seed, so data are the
same on any cluster and in any SQL engine."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import response_models as M
from ..functions.draws import uniform_draw

MODELS = ("graded", "nominal", "nominal_guess", "binary", "step")


def scaled(df: DataFrame, column: str, name: str, low: float = 0.0, high: float = 1.0) -> DataFrame:
    """A column's values stretched to [low, high]."""
    ends = df.agg(F.min(column).alias("_lo"), F.max(column).alias("_hi"))
    at = (F.col(column) - F.col("_lo")) / (F.col("_hi") - F.col("_lo"))
    return df.crossJoin(F.broadcast(ends)).withColumn(name, F.when(F.col("_hi") > F.col("_lo"), at * (high - low) + low).otherwise(F.lit(low))).drop("_lo", "_hi")


def users_from(df: DataFrame, key: str, value: str, most: int | None = None, low: float = 0.0, high: float = 1.0) -> DataFrame:
    """user_id, theta: ability from a column, for ids up to ``most``."""
    some = df.where(F.col(key) <= most) if most else df
    return scaled(some.select(F.col(key).cast("long").alias("user_id"), F.col(value).cast("double").alias("v")), "v", "theta", low, high).select("user_id", "theta")


def items_from(df: DataFrame, key: str, most: int, k: int, a_max: float = 10.0, b_low: float = -0.5, b_high: float = 0.5, seed: int = 42) -> DataFrame:
    """item_id, a (one slope), slopes and places (one each for k options), thresholds (k - 1, rising)."""
    ids = df.where(F.col(key) <= most).select(F.col(key).cast("long").alias("item_id"))
    draw = lambda tag, h: uniform_draw("item_id", F.lit(tag), F.lit(h), seed)
    width = b_high - b_low
    return ids.select(
        "item_id",
        (uniform_draw("item_id", F.lit("a"), seed) * a_max).alias("a"),
        F.array(*[draw("s", h) * a_max for h in range(k)]).alias("slopes"),
        F.array(*[draw("b", h) * width + b_low for h in range(k)]).alias("places"),
        F.sort_array(F.array(*[draw("t", h) * width + b_low for h in range(k - 1)])).alias("thresholds"),
    )


def generate(users: DataFrame, items: DataFrame, model: str, seed=42, answered=1.0, guess: float = 0.25, run: bool = False, told: bool = False) -> DataFrame:
    """user_id, item_id, option_id (int), correctness order inside: higher option is better for the
    ordered models; for the nominal ones the option with the steepest slope is correct.

    items are few (they are sent out); ``answered`` keeps that share of all pairs.  With ``run``, users
    and items have a column of that name and many data sets are drawn at once; seed and answered
    may then be columns of items.  With ``told``, answers also say whether they are correct and
    which grade they have (0 worst)."""
    if model not in MODELS:
        raise ValueError(f"model: one of {', '.join(MODELS)}")
    pairs = users.join(F.broadcast(items), "run") if run else users.crossJoin(F.broadcast(items))
    if not isinstance(answered, (int, float)) or answered < 1:
        pairs = pairs.where(uniform_draw("user_id", "item_id", F.lit("keep"), seed) < answered)
    u = uniform_draw("user_id", "item_id", seed)
    theta, a = F.col("theta"), F.col("a")
    if model == "graded":
        option = F.aggregate("thresholds", F.lit(0), lambda n, b: n + F.when(u < M.logistic(a * (theta - b)), 1).otherwise(0))
    elif model == "step":
        option = F.aggregate("thresholds", F.lit(0), lambda n, b: n + F.when(theta >= b, 1).otherwise(0))
    elif model == "binary":
        option = F.when(u < M.p_correct(theta, a, F.element_at("places", 1), guess), 1).otherwise(0)
    else:
        p = M.p_nominal(theta, F.col("slopes"), F.col("places")) if model == "nominal" else M.p_nominal_guess(theta, F.col("slopes"), F.col("places"))
        option = M.draw_option(u, p)
    keys = [*(["run"] if run else []), "user_id", "item_id"]
    drawn = pairs.withColumn("option_id", option.cast("int"))
    if not told:
        return drawn.select(*keys, "option_id")
    if model in ("nominal", "nominal_guess"):
        own = F.element_at("slopes", F.col("option_id") + 1)
        grade = F.size(F.filter("slopes", lambda s, h: (s < own) | ((s == own) & (h < F.col("option_id")))))
        correct = F.col("option_id") == F.array_position("slopes", F.array_max("slopes")) - 1
    else:
        grade = F.col("option_id")
        correct = grade == (F.lit(1) if model == "binary" else F.size("thresholds"))
    return drawn.select(*keys, "option_id", "theta", correct.alias("correct"), grade.cast("int").alias("grade"))


def _first(df: DataFrame, key: str, runs: DataFrame, size: str) -> DataFrame:
    """The rows with the smallest keys, numbered from 1, as many as the largest run needs."""
    most = runs.agg(F.max(size)).first()[0] or 0
    return df.orderBy(key).limit(int(most)).withColumn("_at", F.row_number().over(Window.orderBy(key)))  # bounded by the run's size


def users_of_runs(df: DataFrame, key: str, value: str, runs: DataFrame) -> DataFrame:
    """run, user_id, theta in [0, 1]: for each run its first m users.  runs: few rows."""
    named = df.select(F.col(key).cast("long").alias("user_id"), F.col(value).cast("double").alias("v"))
    some = _first(named, "user_id", runs, "m").join(F.broadcast(runs.select("run", "m")), F.col("_at") <= F.col("m")).drop("_at")
    ends = some.groupBy("run").agg(F.min("v").alias("lo"), F.max("v").alias("hi"))
    return some.join(F.broadcast(ends), "run").select("run", "user_id", F.when(F.col("hi") > F.col("lo"), (F.col("v") - F.col("lo")) / (F.col("hi") - F.col("lo"))).otherwise(0.0).alias("theta"))


def items_of_runs(df: DataFrame, key: str, runs: DataFrame) -> DataFrame:
    """``items_from`` for each run (its first n items; k, a_max, low, high, seed), which keeps seed and answered."""
    some = _first(df.select(F.col(key).cast("long").alias("item_id")), "item_id", runs, "n").join(F.broadcast(runs), F.col("_at") <= F.col("n")).drop("_at")
    draw = lambda tag, h: uniform_draw("item_id", F.lit(tag), h, F.col("seed"))
    place = lambda u: u * (F.col("high") - F.col("low")) + F.col("low")
    options = F.sequence(F.lit(0), F.col("k") - 1)
    return some.select(
        "run", "item_id", "seed", "answered",
        (uniform_draw("item_id", F.lit("a"), F.col("seed")) * F.col("a_max")).alias("a"),
        F.transform(options, lambda h: draw("s", h) * F.col("a_max")).alias("slopes"),
        F.transform(options, lambda h: place(draw("b", h))).alias("places"),
        F.sort_array(F.transform(F.slice(options, 1, F.col("k") - 1), lambda h: place(draw("t", h)))).alias("thresholds"),
    )


def answer_key(items: DataFrame, model: str) -> DataFrame:
    """item_id and its correct option."""
    if model in ("nominal", "nominal_guess"):
        steepest = F.array_position("slopes", F.array_max("slopes")) - 1
        return items.select("item_id", steepest.cast("int").alias("option_id"))
    last = F.lit(1) if model == "binary" else F.size("thresholds")
    return items.select("item_id", last.cast("int").alias("option_id"))


def option_order(items: DataFrame, model: str) -> DataFrame:
    """item_id, option_id, correctness_rank (0 worst)."""
    if model in ("nominal", "nominal_guess"):
        flat = items.select("item_id", F.posexplode("slopes").alias("option_id", "s"))
        return flat.select("item_id", "option_id", (F.row_number().over(Window.partitionBy("item_id").orderBy("s", "option_id")) - 1).alias("correctness_rank"))
    options = F.sequence(F.lit(0), F.lit(1) if model == "binary" else F.size("thresholds"))
    return items.select("item_id", F.explode(options).alias("option_id")).withColumn("correctness_rank", F.col("option_id"))


def relabelled(responses: DataFrame, seed: int = 42) -> DataFrame:
    """Options renamed by hash, so that their numbers tell nothing."""
    return responses.withColumn("option_id", F.substring(F.md5(F.concat_ws("|", F.col("item_id").cast("string"), F.col("option_id").cast("string"), F.lit(str(seed))).cast("binary")), 1, 8))


def consistent(ranked_users: DataFrame, n_items: int) -> DataFrame:
    """Answers whose only consecutive order is the users' (or its reverse): user at rank r has option
    floor((r - 1 - i + n) / n) of item i, so each item parts users at every n-th rank and each pair
    of neighbours is parted by exactly one item.  ranked_users: user_id, r."""
    items = F.sequence(F.lit(1), F.lit(n_items))
    return ranked_users.select("user_id", "r", F.explode(items).alias("item_id")).select("user_id", F.col("item_id").cast("long").alias("item_id"), F.floor((F.col("r") - 1 - F.col("item_id") + n_items) / F.lit(n_items)).cast("int").alias("option_id"))


def evenly_spaced(spark, m: int, n: int, k: int, a: float) -> tuple[DataFrame, DataFrame]:
    """Users and items of the stability runs: abilities and difficulties evenly spaced in [0, 1], all
    items alike in slope, option slopes evenly spaced, options of an item at one place."""
    runs = spark.createDataFrame([(0, m, n, k, float(a))], "run int, m int, n int, k int, a_max double")
    users, items = evenly_spaced_runs(runs)
    return users.drop("run"), items.drop("run")


def evenly_spaced_runs(runs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """``evenly_spaced`` for each run (m, n, k, a_max); items keep the run's other columns."""
    even = lambda x, n: (x - 1) / F.greatest(F.col(n) - 1, F.lit(1))
    users = runs.select("run", "m", F.explode(F.sequence(F.lit(1), F.col("m"))).alias("u")).select("run", F.col("u").cast("long").alias("user_id"), even(F.col("u"), "m").alias("theta"))
    items = runs.withColumn("i", F.explode(F.sequence(F.lit(1), F.col("n"))))
    b = even(F.col("i"), "n")
    kept = [c for c in runs.columns if c not in ("m", "n", "k", "a_max")]
    return users, items.select(
        *kept, F.col("i").cast("long").alias("item_id"), F.col("a_max").alias("a"), F.transform(F.sequence(F.lit(0), F.col("k") - 1), lambda h: F.col("a_max") * h / F.greatest(F.col("k") - 1, F.lit(1))).alias("slopes"),
        F.array_repeat(b, F.col("k")).alias("places"), F.array_repeat(b, F.col("k") - 1).alias("thresholds"),
    )
