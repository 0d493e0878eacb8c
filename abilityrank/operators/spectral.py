"""Difference propagation and its variants: users ordered by the second eigenvector of averaging.

All variants return ``Result``: scores by user_id (first user at 0 or mean-free), the rounds run and
the change norm after each.  The direction is arbitrary until ``orient`` fixes it.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import OPTION, Opts, SizeGuardError, option_dictionary
from ..plans.storage import forget, written
from . import linalg


#: Up to so many options the rounds run on the options' own matrix (18 MB at most).
AUTO_OPTIONS = 1_500


@dataclass
class Result:
    scores: DataFrame
    rounds: int
    trace: list[dict] = field(default_factory=list)

    def trace_df(self, spark) -> DataFrame:
        return spark.createDataFrame(self.trace, "iter int, delta double, rayleigh double, millis long")


def encoded(responses: DataFrame) -> tuple[DataFrame, int, DataFrame]:
    """(answers with dense option numbers, number of options, dictionary)."""
    book = written(option_dictionary(responses), "options")
    return responses.join(book, OPTION), book.count(), book


def gram(responses: DataFrame, n_options: int, block: int = 512) -> np.ndarray:
    """W with W[o, p] = mean over the users of o of (their share that p has): one pass over answers.

    The order of multiplication is turned round: averaging users then options acts on options, and
    its matrix has no more rows than there are options, however many users there are.  Each task
    multiplies blocks of its users' rows (a row has at most one option an item) and hands on one
    matrix, so what is shuffled does not grow with the users.
    """
    import pyarrow as pa

    def add(batches):
        total = np.zeros((n_options, n_options))
        for batch in batches:
            size = batch.column(0).value_lengths().to_numpy()
            flat, ends = batch.column(0).flatten().to_numpy(), np.append(0, np.cumsum(size))
            for lo in range(0, len(size), block):
                own = size[lo : lo + block]
                x = np.zeros((len(own), n_options))
                x[np.repeat(np.arange(len(own)), own), flat[ends[lo] : ends[min(lo + block, len(size))]]] = 1
                total += (x / own[:, None]).T @ x
        at = np.flatnonzero(total)
        for lo in range(0, len(at), 1 << 18):
            part = at[lo : lo + (1 << 18)]
            yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(total.ravel()[part])], ["cell", "x"])

    counted = _packed(responses).select("o").mapInArrow(add, "cell long, x double").groupBy("cell").agg(F.sum("x").alias("x")).toArrow()  # at most options squared, guarded by the caller
    w = np.zeros(n_options * n_options)
    w[counted.column("cell").to_numpy()] = counted.column("x").to_numpy()
    w = w.reshape(n_options, n_options)
    sizes = w.sum(1)
    return w / np.where(sizes > 0, sizes, 1)[:, None]


def _weights_df(spark, w: np.ndarray) -> DataFrame:
    return spark.createDataFrame([(i, float(x)) for i, x in enumerate(w)], "option_ix long, weight double")


def _driver_rounds(w: np.ndarray, start: np.ndarray, votes: np.ndarray, opts: Opts) -> tuple[np.ndarray, list[dict]]:
    """Power rounds in option space, mean-free by votes; the change is of unit vectors."""
    x, trace = start, []
    old = None
    limit = opts.rounds if opts.rounds is not None else opts.max_iter
    for k in range(1, limit + 1):
        began = time.time()
        y = w @ x
        y = y - (votes @ y) / votes.sum()
        norm = float(np.linalg.norm(y))
        if norm == 0:
            x = y
            break
        y /= norm
        delta = float(np.linalg.norm(y - old)) if old is not None else float("inf")
        trace.append({"iter": k, "delta": delta, "rayleigh": float(y @ (w @ y)), "millis": int(1000 * (time.time() - began))})
        x = old = y
        if opts.rounds is None and delta < opts.tol:
            break
    return x, trace


def _gram_power(responses: DataFrame, opts: Opts) -> Result:
    rows, n, _ = encoded(responses)
    if n > opts.max_options:
        raise SizeGuardError(f"{n} options: the option matrix is quadratic; use path='sql'")
    spark = responses.sparkSession
    rows = linalg.layout(rows)
    w = gram(rows, n)
    scores = linalg.initial_scores(responses, opts.seed)
    begun = rows.join(scores, "user_id").groupBy("option_ix").agg(F.avg("score").alias("weight"), F.count("*").alias("n")).toArrow()
    x, votes = np.zeros(n), np.zeros(n)
    x[begun.column("option_ix").to_numpy()] = begun.column("weight").to_numpy()
    votes[begun.column("option_ix").to_numpy()] = begun.column("n").to_numpy()
    some = opts if opts.rounds is None else Opts(**{**opts.__dict__, "rounds": max(0, opts.rounds - 1)})
    x, trace = _driver_rounds(w, x - (votes @ x) / votes.sum(), votes, some)
    final = rows.join(F.broadcast(_weights_df(spark, x)), "option_ix").groupBy("user_id").agg(F.avg("weight").alias("score"))
    return Result(linalg.anchored(final), len(trace) + (opts.rounds is not None), trace)


def _packed(rows: DataFrame) -> DataFrame:
    return rows.groupBy("user_id").agg(F.collect_list("option_ix").alias("o"))


def _arrow_power(responses: DataFrame, opts: Opts) -> Result:
    """Rounds over packed rows: the weights are sent out, each batch adds up its options at once."""
    import pyarrow as pa

    rows, n, _ = encoded(responses)
    if n > linalg.BROADCAST_OPTIONS:
        raise SizeGuardError(f"{n} options: too many to send out each round; use path='sql'")
    spark = responses.sparkSession
    packed = written(_packed(rows), "packed")
    seeds = linalg.initial_scores(responses, opts.seed)
    begun = rows.join(seeds, "user_id").groupBy("option_ix").agg(F.avg("score").alias("weight"), F.count("*").alias("n")).toArrow()
    x, votes = np.zeros(n), np.ones(n)
    x[begun.column("option_ix").to_numpy()] = begun.column("weight").to_numpy()
    votes[begun.column("option_ix").to_numpy()] = begun.column("n").to_numpy()
    x = x - (votes @ x) / votes.sum()
    limit, trace, old = (opts.rounds - 1 if opts.rounds is not None else opts.max_iter), [], None

    def means(batch, w):
        o = batch.column(1)
        size = o.value_lengths().to_numpy()
        flat = o.flatten().to_numpy()
        return flat, size, np.add.reduceat(w[flat], np.cumsum(size) - size) / size if len(size) else np.zeros(0)

    for k in range(1, limit + 1):
        began = time.time()
        sent = spark.sparkContext.broadcast(x)

        def add(batches):
            total = np.zeros(n)
            for batch in batches:
                flat, size, s = means(batch, sent.value)
                total += np.bincount(flat, weights=np.repeat(s, size), minlength=n)
            at = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["option_ix", "x"])

        sums = packed.mapInArrow(add, "option_ix long, x double").groupBy("option_ix").agg(F.sum("x").alias("x")).toArrow()
        y = np.zeros(n)
        y[sums.column("option_ix").to_numpy()] = sums.column("x").to_numpy()
        y /= votes
        y -= (votes @ y) / votes.sum()
        norm = np.linalg.norm(y)
        quotient = float(x @ y / (x @ x)) if x.any() else None
        sent.unpersist()
        if norm == 0:
            x = y
            break
        y /= norm
        delta = float(np.linalg.norm(y - old)) if old is not None else float("inf")
        trace.append({"iter": k, "delta": delta, "rayleigh": quotient, "millis": int(1000 * (time.time() - began))})
        x = old = y
        if opts.rounds is None and delta < opts.tol:
            break
    sent = spark.sparkContext.broadcast(x)

    def score(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(means(batch, sent.value)[2])], ["user_id", "score"])

    return Result(linalg.anchored(packed.mapInArrow(score, "user_id long, score double")), len(trace) + 1, trace)


def _unit_diffs(scores: DataFrame, pos: DataFrame) -> DataFrame:
    d = linalg.to_diffs(scores, pos)
    norm = d.agg(F.sqrt(F.sum(F.col("diff") * F.col("diff"))).alias("norm"))
    return d.crossJoin(F.broadcast(norm)).select("pos", F.when(F.col("norm") > 0, F.col("diff") / F.col("norm")).otherwise(0.0).alias("diff"))


def _sql_power(responses: DataFrame, opts: Opts, step: str, init: DataFrame | None) -> Result:
    rows = linalg.layout(responses)
    n_options = rows.select(*OPTION).distinct().count()
    pos = written(linalg.positions(responses), "positions") if step == "diff" or opts.rounds is None else None
    scores = init if init is not None else linalg.initial_scores(rows, opts.seed)
    old, trace = None, []
    limit = opts.rounds if opts.rounds is not None else opts.max_iter
    for k in range(1, limit + 1):
        began = time.time()
        if step == "diff":  # differences back to scores, from 0 on
            scores = linalg.from_diffs(linalg.to_diffs(scores, pos), pos)
        before = scores
        _, scores = linalg.avg_step(rows, scores, n_options)
        scores = linalg.anchored(scores)
        if before is not init:
            forget(before)
        last = k == limit
        measured = opts.rounds is None and (k % opts.check_every == 0 or last)
        if measured:
            new = written(_unit_diffs(scores, pos), "diffs")
            delta = float("inf") if old is None else new.join(old.select("pos", F.col("diff").alias("before")), "pos").agg(F.sqrt(F.sum(F.pow(F.col("diff") - F.col("before"), 2)))).first()[0]
            trace.append({"iter": k, "delta": float(delta), "rayleigh": None, "millis": int(1000 * (time.time() - began))})
            forget(old)
            old = new
            if delta < opts.tol:
                break
    return Result(scores, k if limit else 0, trace)


def diffprop_power(responses: DataFrame, opts: Opts = Opts(), step: str = "anchored", init: DataFrame | None = None) -> Result:
    """The main method.

    step 'diff' goes through differences in every round; 'anchored' takes the first user's score off
    instead, which is the same in exact arithmetic.  path 'gram' runs the rounds on the option
    matrix, 'arrow' over packed rows, 'sql' as joins; 'auto' takes gram where the options allow it.
    """
    if step not in ("anchored", "diff"):
        raise ValueError("step: anchored or diff")
    path = opts.path
    if path == "auto":
        few = responses.select(*OPTION).distinct().limit(min(opts.max_options, AUTO_OPTIONS) + 1).count() <= min(opts.max_options, AUTO_OPTIONS)
        path = "gram" if few and step == "anchored" and init is None else "sql"
    if path == "gram":
        return _gram_power(responses, opts)
    if path == "arrow":
        return _arrow_power(responses, opts)
    return _sql_power(responses, opts, step, init)


def dense_answers(responses: DataFrame, most_users: int) -> tuple[list, np.ndarray]:
    """(user ids in order, users x options 0/1 matrix) on the driver, for few users only."""
    users = [r[0] for r in responses.select("user_id").distinct().orderBy("user_id").limit(most_users + 1).collect()]
    if len(users) > most_users:
        raise SizeGuardError(f"more than {most_users} users: the matrix is quadratic; use the power variant")
    table = encoded(responses)[0].select("user_id", "option_ix").toArrow()
    at = {u: i for i, u in enumerate(users)}
    cols = table.column("option_ix").to_numpy()
    c = np.zeros((len(users), int(cols.max(initial=-1)) + 1))
    c[[at[u] for u in table.column("user_id").to_pylist()], cols] = 1
    return users, c


def _from_driver(responses: DataFrame, users: list, scores: np.ndarray) -> DataFrame:
    return responses.sparkSession.createDataFrame([(u, float(s)) for u, s in zip(users, scores)], "user_id long, score double")


def narrow(responses: DataFrame, opts: Opts) -> tuple[linalg.Held, list[np.ndarray]] | None:
    """Index arrays and levels of more than max_users users, where no level has more than a twentieth of that;
    None for fewer users, or wide levels."""
    if responses.select("user_id").distinct().limit(opts.max_users + 1).count() <= opts.max_users:
        return None
    held = linalg.Held(responses)
    levels = held.levels()
    return (held, levels) if max(map(len, levels)) <= opts.max_users // 20 else None


def averaging_matrix(c: np.ndarray) -> np.ndarray:
    return (c / c.sum(1, keepdims=True)) @ (c / c.sum(0, keepdims=True)).T


def diffprop_direct(responses: DataFrame, opts: Opts = Opts()) -> Result:
    """Second eigenvector from the symmetric matrix that averaging is similar to; of more users than
    ``max_users`` from its factors by levels, where these are narrow."""
    found = narrow(responses, opts)
    if found is not None:
        held, levels = found
        answers = np.diff(held.starts).astype(float)
        vector = linalg.narrow_vector(held, 1.0 / held.sizes, answers, answers, levels, opts.seed)
        return Result(linalg.anchored(_from_driver(responses, held.ids.tolist(), vector)), 0)
    users, c = dense_answers(responses, opts.max_users)
    root = np.sqrt(c.sum(1))
    half = c / root[:, None]
    _, vectors = np.linalg.eigh((half / c.sum(0)) @ half.T)
    return Result(linalg.anchored(_from_driver(responses, users, vectors[:, -2] / root if len(users) > 1 else np.zeros(len(users)))), 0)


def diffprop_naive(responses: DataFrame, opts: Opts = Opts()) -> Result:
    """Power rounds on the explicit difference matrix, with differences taken along the users' levels: cells far
    from the diagonal, which are 0 where levels are narrow, are left out.

    Rounds grow with the square of the number of levels: the trace has each of the first thousand, then
    each thousandth."""
    held = linalg.Held(responses)
    held = held.reordered(np.concatenate([*held.levels(), np.zeros(0, np.int64)]).astype(np.int64))
    blocks = linalg.difference_blocks(held)
    d = np.random.default_rng(opts.seed).random(max(len(held.ids) - 1, 0))
    trace, rounds = [], 0
    for rounds in range(1, (opts.rounds or opts.max_iter) + 1):
        began = time.time()
        new = np.empty_like(d)
        for lo, first, cells in blocks:
            np.dot(cells, d[first : first + cells.shape[1]], out=new[lo : lo + len(cells)])
        traced = rounds <= 1000 or rounds % 1000 == 0
        quotient = float(d @ new / (d @ d)) if traced and d.any() else None
        norm = np.linalg.norm(new)
        new = new / norm if norm else new
        delta = float(np.linalg.norm(new - d))
        if traced:
            trace.append({"iter": rounds, "delta": delta, "rayleigh": quotient, "millis": int(1000 * (time.time() - began))})
        d = new
        if opts.rounds is None and delta < opts.tol:
            break
    return Result(linalg.anchored(_from_driver(responses, held.ids.tolist(), np.append(0.0, np.cumsum(d))[: len(held.ids)])), rounds, trace)


def left_vector(responses: DataFrame, opts: Opts = Opts()) -> DataFrame:
    """The dominant left eigenvector of averaging by power rounds of the transpose; its limit is the
    number of answers of each user."""
    rows = linalg.layout(responses)
    n = rows.groupBy("user_id").agg(F.count("*").alias("n"))
    sizes = rows.groupBy(*OPTION).agg(F.count("*").alias("n_o"))
    l = n.select("user_id", F.lit(1.0).alias("score"))
    for _ in range(opts.rounds or 10):
        shared = l.join(n, "user_id").select("user_id", (F.col("score") / F.col("n")).alias("score"))
        y = linalg.option_sums(rows, shared).join(sizes, OPTION).select(*OPTION, (F.col("weight") / F.col("n_o")).alias("weight"))
        l = written(linalg.user_sums(rows, y), "left")
    total = l.agg(F.sum("score").alias("total"))
    return l.crossJoin(F.broadcast(total)).select("user_id", (F.col("score") / F.col("total")).alias("score"))


def diffprop_deflation(responses: DataFrame, opts: Opts = Opts(), left: str = "closed_form", scheme: str = "hotelling") -> Result:
    """Power rounds with the dominant direction taken out.

    hotelling: the mean weighted by the left vector goes, which is known (answers per user) or found
    by a power phase of its own.  annihilate: only the right vector is used, as in the anchored step.
    symmetrised: on the symmetric similar matrix; a plain symmetric scheme does not apply.
    """
    if scheme == "symmetric":
        raise ValueError("averaging is not symmetric: use scheme='symmetrised'")
    if scheme == "annihilate":
        return _sql_power(responses, opts, "anchored", None)
    if scheme == "symmetrised":
        users, c = dense_answers(responses, opts.max_users)
        root = np.sqrt(c.sum(1))
        half = c / root[:, None]
        a = (half / c.sum(0)) @ half.T
        top = root / np.linalg.norm(root)
        x, k = np.random.default_rng(opts.seed).random(len(users)), 0
        for k in range(1, (opts.rounds or opts.max_iter) + 1):
            y = a @ (x - top * (top @ x))
            y /= np.linalg.norm(y) or 1
            change, x = np.linalg.norm(y - x), y
            if opts.rounds is None and change < opts.tol:
                break
        return Result(linalg.anchored(_from_driver(responses, users, x / root)), k)
    rows = linalg.layout(responses)
    weight = rows.groupBy("user_id").agg(F.count("*").cast("double").alias("l")) if left == "closed_form" else left_vector(responses, opts).withColumnRenamed("score", "l")
    weight = written(weight, "left")
    n_options = rows.select(*OPTION).distinct().count()
    scores, trace, old, k = linalg.initial_scores(rows, opts.seed), [], None, 0
    for k in range(1, (opts.rounds if opts.rounds is not None else opts.max_iter) + 1):
        began = time.time()
        mean = scores.join(weight, "user_id").agg(F.sum(F.col("l") * F.col("score")) / F.sum("l")).first()[0]
        _, scores = linalg.avg_step(rows, scores.select("user_id", (F.col("score") - F.lit(mean)).alias("score")), n_options)
        scores = written(scores, "scores")
        size = scores.agg(F.max(F.abs("score"))).first()[0]
        scores = scores.select("user_id", (F.col("score") / F.lit(size or 1.0)).alias("score"))
        if opts.rounds is None and k % opts.check_every == 0:
            delta = float("inf") if old is None else scores.join(old.withColumnRenamed("score", "before"), "user_id").agg(F.sqrt(F.sum(F.pow(F.col("score") - F.col("before"), 2)))).first()[0]
            trace.append({"iter": k, "delta": float(delta), "rayleigh": None, "millis": int(1000 * (time.time() - began))})
            old = scores
            if delta < opts.tol:
                break
    return Result(scores, k, trace)


def avghits(responses: DataFrame, opts: Opts = Opts()) -> Result:
    """Averaging without any deflation: scores go to one constant."""
    rows = linalg.layout(responses)
    n_options = rows.select(*OPTION).distinct().count()
    scores = linalg.initial_scores(rows, opts.seed)
    k = 0
    for k in range(1, (opts.rounds or opts.max_iter) + 1):
        _, scores = linalg.avg_step(rows, scores, n_options)
        scores = written(scores, "scores")
        if opts.rounds is None:
            spread = scores.agg(F.max("score") - F.min("score")).first()[0]
            if spread < opts.tol:
                break
    return Result(scores, k)
