"""Fiedler seriation: users ordered by the second-smallest Laplacian eigenvector of co-answering."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import OPTION, Opts
from ..plans.storage import forget, written
from . import linalg
from .spectral import Result, _from_driver, _unit_diffs, dense_answers, narrow


def co_answers(responses: DataFrame) -> DataFrame:
    """u, v, n: how many options two users share; quadratic in users."""

    def make(held, columns, lo, hi):
        n = held.rows(lo, hi, columns, False)
        u, v = np.nonzero(n)
        return held.ids[lo + u], held.ids[v], n[u, v].astype(np.int64)

    held = linalg.Held(responses)
    return linalg.by_rows(responses.sparkSession, held, make, "u long, v long, n long", len(held.ids))


def laplacian(responses: DataFrame) -> DataFrame:
    """u, v, value: row sums on the diagonal, less the shared options; zeros left out."""
    off = co_answers(responses).where("u <> v").select("u", "v", (-F.col("n")).alias("value"))
    sizes = responses.groupBy(*OPTION).agg((F.count("*") - 1).alias("others"))
    diagonal = responses.join(sizes, OPTION).groupBy("user_id").agg(F.sum("others").alias("value")).where("value > 0")
    return off.unionByName(diagonal.select(F.col("user_id").alias("u"), F.col("user_id").alias("v"), "value"))


def degrees(responses: DataFrame) -> DataFrame:
    """user_id, degree: choosers of all of the user's options, the user included each time."""
    sizes = responses.groupBy(*OPTION).agg(F.count("*").alias("n_o"))
    return responses.join(sizes, OPTION).groupBy("user_id").agg(F.sum("n_o").cast("double").alias("degree"))


def fiedler_direct(responses: DataFrame, opts: Opts = Opts(), solver: str = "eigh") -> Result:
    """From the explicit Laplacian of few users, of more by its factors (``narrow_vector``); 'lanczos' only
    multiplies by the answer matrix."""
    found = narrow(responses, opts) if solver == "eigh" else None
    if found is not None:
        held, levels = found
        degree = np.add.reduceat(held.sizes[held.option], held.starts[:-1]).astype(float)
        vector = linalg.narrow_vector(held, np.ones(len(held.sizes)), degree, np.ones(len(degree)), levels, opts.seed)
        return Result(linalg.anchored(_from_driver(responses, held.ids.tolist(), vector)), 0)
    users, c = dense_answers(responses, opts.max_users)
    if len(users) < 2:
        return Result(_from_driver(responses, users, np.zeros(len(users))), 0)
    d = c @ c.sum(0)
    if solver == "eigh":
        _, vectors = np.linalg.eigh(np.diag(d) - c @ c.T)
        return Result(linalg.anchored(_from_driver(responses, users, vectors[:, 1])), 0)
    vector, steps = _lanczos(lambda x: d * x - c @ (c.T @ x), len(users), opts.seed)
    return Result(linalg.anchored(_from_driver(responses, users, vector)), steps)


def _lanczos(times, n: int, seed: int) -> tuple[np.ndarray, int]:
    """Smallest eigenvector orthogonal to the constant, with full reorthogonalisation."""
    ones = np.full(n, n**-0.5)
    q = np.random.default_rng(seed).standard_normal(n)
    q -= ones * (ones @ q)
    basis, alpha, beta = [q / np.linalg.norm(q)], [], []
    for _ in range(n - 1):
        z = times(basis[-1])
        alpha.append(basis[-1] @ z)
        for b in [ones, *basis]:
            z = z - b * (b @ z)
        for b in [ones, *basis]:
            z = z - b * (b @ z)
        size = np.linalg.norm(z)
        if size < 1e-10 or len(alpha) == n - 1:
            break
        beta.append(size)
        basis.append(z / size)
    k = len(alpha)
    _, s = np.linalg.eigh(np.diag(alpha) + np.diag(beta[: k - 1], 1) + np.diag(beta[: k - 1], -1))
    return np.array(basis[:k]).T @ s[:, 0], k


def fiedler_power(responses: DataFrame, opts: Opts = Opts(), beta: float | None = None, step: str = "anchored") -> Result:
    """Power rounds on the Laplacian taken from a multiple of the identity; nothing is quadratic."""
    rows = linalg.layout(responses)
    n_options = rows.select(*OPTION).distinct().count()
    degree = written(degrees(rows), "degrees")
    if beta is None:  # no eigenvalue exceeds twice the largest diagonal entry
        beta = 2.0 * (degree.agg(F.max("degree")).first()[0] or 0.0)
    pos = written(linalg.positions(responses), "positions") if step == "diff" or opts.rounds is None else None
    scores, old, trace, k = linalg.initial_scores(rows, opts.seed), None, [], 0
    for k in range(1, (opts.rounds if opts.rounds is not None else opts.max_iter) + 1):
        began = time.time()
        if step == "diff":
            scores = linalg.from_diffs(linalg.to_diffs(scores, pos), pos)
        shared = linalg.user_sums(rows, linalg.option_sums(rows, scores), n_options).withColumnRenamed("score", "z")
        moved = scores.join(degree, "user_id").join(shared, "user_id").select("user_id", ((F.lit(beta) - F.col("degree")) * F.col("score") + F.col("z")).alias("score"))
        before, scores = scores, linalg.anchored(moved)
        forget(before)
        if opts.rounds is None and k % opts.check_every == 0:
            new = written(_unit_diffs(scores, pos), "diffs")
            delta = float("inf") if old is None else new.join(old.select("pos", F.col("diff").alias("before")), "pos").agg(F.sqrt(F.sum(F.pow(F.col("diff") - F.col("before"), 2)))).first()[0]
            trace.append({"iter": k, "delta": float(delta), "rayleigh": None, "millis": int(1000 * (time.time() - began))})
            forget(old)
            old = new
            if delta < opts.tol:
                break
    return Result(scores, k, trace)
