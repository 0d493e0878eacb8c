"""A baseline that is told the order of each item's options: the graded model fitted by marginal
maximum likelihood, with abilities as posterior means.

Curves are kept as slope and intercepts: the chance of reaching grade h is logistic(a x - c_h).
Both the rounds over a DataFrame and those over one small data set use the same two steps here:
``curves`` to weigh a user's nodes and ``improve`` to fit all items to their expected counts.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Opts
from ..plans.storage import written
from .spectral import Result

UNUSED = 40.0  # an intercept that nobody reaches: items with fewer grades are filled up with it


def nodes(n: int = 41) -> tuple[np.ndarray, np.ndarray]:
    x = np.linspace(-4, 4, n)
    w = np.exp(-x * x / 2)
    return x, w / w.sum()


def _reaching(a: np.ndarray, c: np.ndarray, x: np.ndarray) -> np.ndarray:
    """items x nodes x (grades - 1)"""
    return 1 / (1 + np.exp(-np.clip(a[:, None, None] * x[None, :, None] - c[:, None, :], -35, 35)))


def _between(reach: np.ndarray) -> np.ndarray:
    j, q, _ = reach.shape
    full = np.concatenate([np.ones((j, q, 1)), reach, np.zeros((j, q, 1))], 2)
    return np.maximum(full[:, :, :-1] - full[:, :, 1:], 1e-9)


def curves(a: np.ndarray, c: np.ndarray, x: np.ndarray) -> np.ndarray:
    """items x nodes x grades probabilities."""
    return _between(_reaching(a, c, x))


def _value(a: np.ndarray, c: np.ndarray, counts: np.ndarray, x: np.ndarray) -> np.ndarray:
    return (counts * np.log(curves(a, c, x))).sum((1, 2)) - 0.5 * np.log(a) ** 2


def improve(a: np.ndarray, c: np.ndarray, counts: np.ndarray, x: np.ndarray, steps: int = 4) -> tuple[np.ndarray, np.ndarray]:
    """Scoring steps on the expected log-likelihood of every item, each halved until it gains; the
    logarithms of slopes have a standard normal prior."""
    used = c < UNUSED
    for _ in range(steps):
        reach = _reaching(a, c, x)
        p = _between(reach)
        q = reach * (1 - reach) * used[:, None, :]
        j, n, k = p.shape
        slope = np.zeros((j, n, k, k))  # of each grade's probability by a and by each intercept
        slope[:, :, 1:, 0] += x[None, :, None] * q
        slope[:, :, :-1, 0] -= x[None, :, None] * q
        for h in range(k - 1):
            slope[:, :, h + 1, h + 1] -= q[:, :, h]
            slope[:, :, h, h + 1] += q[:, :, h]
        grad = np.einsum("jnk,jnkp->jp", counts / p, slope)
        info = np.einsum("jn,jnkp,jnkr->jpr", counts.sum(2), slope / p[..., None], slope)
        grad[:, 0] -= np.log(a) / a
        info[:, 0, 0] += 1 / a**2
        info += np.eye(k) * 1e-6
        move = np.linalg.solve(info, grad[:, :, None])[:, :, 0]
        now, size, todo = _value(a, c, counts, x), np.ones(j), np.ones(j, bool)
        for _ in range(6):
            new_a = np.clip(a + size * move[:, 0], 0.05, 20)
            new_c = np.sort(np.where(used, c + size[:, None] * move[:, 1:], UNUSED), 1)
            better = todo & (_value(new_a, new_c, counts, x) >= now)
            a, c = np.where(better, new_a, a), np.where(better[:, None], new_c, c)
            todo &= ~better
            if not todo.any():
                break
            size[todo] /= 2
    return a, c


def start(grades: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Slopes and intercepts to begin with, for items with these numbers of grades."""
    most = max(2, int(grades.max(initial=2)))
    at = np.arange(1, most)[None, :]
    c = np.where(at < grades[:, None], 2.0 * at / np.maximum(grades[:, None], 2) - 1.0, UNUSED)
    return np.ones(len(grades)), c


def _weighed(logs: np.ndarray, prior: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(posterior of each row, log-likelihood of each row) from sums of log-probabilities by node."""
    z = logs + np.log(prior)
    top = z.max(1, keepdims=True)
    e = np.exp(z - top)
    total = e.sum(1, keepdims=True)
    return e / total, (top + np.log(total))[:, 0]


def _by_row(user: np.ndarray, item: np.ndarray, grade: np.ndarray, rows: int, logs: np.ndarray) -> np.ndarray:
    """rows x nodes sums of the answers' log-probabilities; logs: items x grades x nodes."""
    flat, picked = logs.reshape(-1, logs.shape[2]), item * logs.shape[1] + grade
    return np.stack([np.bincount(user, flat[picked, q], rows) for q in range(flat.shape[1])], 1)


def _counts(user: np.ndarray, item: np.ndarray, grade: np.ndarray, posterior: np.ndarray, items: int, grades: int) -> np.ndarray:
    cell = item * grades + grade
    return np.stack([np.bincount(cell, posterior[user, q], items * grades) for q in range(posterior.shape[1])], 1).reshape(items, grades, -1).transpose(0, 2, 1)


def abilities(user: np.ndarray, item: np.ndarray, grade: np.ndarray, tol: float = 1e-5, rounds: int = 200) -> np.ndarray:
    """Posterior means for one small data set of index arrays; ends when the log-likelihood of an answer
    gains less than ``tol`` a round."""
    x, prior = nodes()
    m, n = int(user.max(initial=-1)) + 1, int(item.max(initial=-1)) + 1
    if not m:
        return np.zeros(0)
    most = np.zeros(n, np.int64)
    np.maximum.at(most, item, grade + 1)
    a, c = start(most)
    old = -np.inf
    for _ in range(rounds):
        posterior, value = _weighed(_by_row(user, item, grade, m, np.log(curves(a, c, x)).transpose(0, 2, 1)), prior)
        total = value.sum() / len(user)
        if total - old < tol:
            break
        old = total
        a, c = improve(a, c, _counts(user, item, grade, posterior, n, c.shape[1] + 1), x)
    return posterior @ x


def graded_estimator(responses: DataFrame, order: DataFrame, opts: Opts = Opts(max_iter=200)) -> Result:
    """order: item_id, option_id, correctness_rank (0 worst).  Scores are posterior mean abilities.

    A round sends out item parameters (items x grades), weighs each user's nodes where the user's
    answers are, adds up expected counts by item and fits items in executors, a block of them a task.
    It ends when the log-likelihood of an answer gains less than ``opts.tol``.
    """
    spark = responses.sparkSession
    x, prior = nodes()
    names = written(order.groupBy("item_id").agg((F.max("correctness_rank") + 1).alias("k")).select(F.col("item_id").cast("string").alias("item_id"), "k"), "items").orderBy("item_id").toPandas()  # one row an item, as the parameters that each round sends out
    at = {i: j for j, i in enumerate(names["item_id"])}
    a, c = start(names["k"].to_numpy(np.int64))
    grades = c.shape[1] + 1
    numbered = spark.createDataFrame([(i, j) for i, j in at.items()], "item_id string, item int")
    rows = responses.join(order, ["item_id", "option_id"]).select("user_id", F.col("item_id").cast("string").alias("item_id"), F.col("correctness_rank").cast("int").alias("grade")).join(F.broadcast(numbered), "item_id")
    packed = written(rows.groupBy("user_id").agg(F.collect_list("item").alias("items"), F.collect_list("grade").alias("grades")), "graded")
    answers = rows.count()

    def laid(pdf):
        sizes = pdf["items"].map(len).to_numpy()
        flat = lambda column: np.concatenate([np.asarray(v) for v in pdf[column]]).astype(np.int64) if len(pdf) else np.zeros(0, np.int64)
        return np.repeat(np.arange(len(pdf)), sizes), flat("items"), flat("grades")

    k, old = 0, -np.inf
    for k in range(1, (opts.rounds or opts.max_iter) + 1):
        sent = spark.sparkContext.broadcast((a, c))

        def expect(batches):
            logs = np.log(curves(*sent.value, x)).transpose(0, 2, 1)
            total, value = np.zeros((len(logs), len(x), grades)), 0.0
            for pdf in batches:
                user, item, grade = laid(pdf)
                posterior, gained = _weighed(_by_row(user, item, grade, len(pdf), logs), prior)
                total += _counts(user, item, grade, posterior, len(logs), grades)
                value += float(gained.sum())
            seen = np.flatnonzero(total.any((1, 2)))
            yield pd.DataFrame({"block": -1, "item": [-1], "counts": [[value]]})
            yield pd.DataFrame({"block": seen // 256, "item": seen, "counts": list(total[seen].reshape(len(seen), -1))})

        def fit(key, pdf):
            if key[0] < 0:
                return pd.DataFrame({"item": [-1], "a": [float(sum(v[0] for v in pdf["counts"]))], "c": [[]]})
            one = pdf.groupby("item")["counts"].agg(lambda v: np.sum([np.asarray(z) for z in v], 0))
            own = one.index.to_numpy()
            old_a, old_c = sent.value
            new_a, new_c = improve(old_a[own], old_c[own], np.stack(list(one)).reshape(len(own), len(x), grades), x)
            return pd.DataFrame({"item": own, "a": new_a, "c": list(new_c)})

        fitted = packed.mapInPandas(expect, "block int, item int, counts array<double>").groupBy("block").applyInPandas(fit, "item int, a double, c array<double>").collect()
        value = sum(r["a"] for r in fitted if r["item"] < 0) / max(answers, 1)
        if opts.rounds is None and value - old < opts.tol:
            break
        old = value
        a, c = a.copy(), c.copy()
        for r in fitted:
            if r["item"] >= 0:
                a[r["item"]], c[r["item"]] = r["a"], r["c"]
    sent = spark.sparkContext.broadcast((a, c))

    def means(batches):
        logs = np.log(curves(*sent.value, x)).transpose(0, 2, 1)
        for pdf in batches:
            user, item, grade = laid(pdf)
            yield pd.DataFrame({"user_id": pdf["user_id"], "score": _weighed(_by_row(user, item, grade, len(pdf), logs), prior)[0] @ x})

    return Result(packed.mapInPandas(means, "user_id long, score double"), k)
