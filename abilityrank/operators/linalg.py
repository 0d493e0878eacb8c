"""Sparse steps between users and options, and between scores and their adjacent differences.

Option sums are partial sums of rows that stay where their users are, so a round has one shuffle of
at most (partitions x options) rows; weights go back by broadcast below a size that is checked.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.draws import uniform_draw
from ..model import OPTION, SizeGuardError
from ..plans.storage import derived, written

BROADCAST_OPTIONS = 5_000_000


def layout(responses: DataFrame, partitions: int | None = None) -> DataFrame:
    """Answers by user, kept for all rounds: the last time that they move."""
    rows = responses.repartition(partitions, "user_id") if partitions else responses.repartition("user_id")
    return rows.persist()


def initial_scores(responses: DataFrame, seed: int = 42) -> DataFrame:
    return responses.select("user_id").distinct().select("user_id", uniform_draw("user_id", seed).alias("score"))


def option_means(responses: DataFrame, scores: DataFrame) -> DataFrame:
    return responses.join(scores, "user_id").groupBy(*OPTION).agg(F.avg("score").alias("weight"))


def option_sums(responses: DataFrame, scores: DataFrame) -> DataFrame:
    return responses.join(scores, "user_id").groupBy(*OPTION).agg(F.sum("score").alias("weight"))


def _back(responses: DataFrame, weights: DataFrame, n_options: int | None) -> DataFrame:
    small = n_options is not None and n_options <= BROADCAST_OPTIONS
    return responses.join(F.broadcast(weights) if small else weights, OPTION)


def user_means(responses: DataFrame, weights: DataFrame, n_options: int | None = None) -> DataFrame:
    return _back(responses, weights, n_options).groupBy("user_id").agg(F.avg("weight").alias("score"))


def user_sums(responses: DataFrame, weights: DataFrame, n_options: int | None = None) -> DataFrame:
    return _back(responses, weights, n_options).groupBy("user_id").agg(F.sum("weight").alias("score"))


def avg_step(responses: DataFrame, scores: DataFrame, n_options: int | None = None) -> tuple[DataFrame, DataFrame]:
    """One averaging round: (weights, scores)."""
    weights = option_means(responses, scores)
    return weights, user_means(responses, weights, n_options)


def anchored(scores: DataFrame) -> DataFrame:
    """The first user's score taken off, then divided by the largest size.

    Scores are written once (the lineage of a loop is cut there, and a lost executor costs a read);
    three numbers come back to the driver."""
    kept = written(scores, "scores")
    ends = kept.agg(F.min_by("score", "user_id").alias("anchor"), F.min("score").alias("low"), F.max("score").alias("high")).first()
    if ends["anchor"] is None:
        return kept
    size = max(abs(ends["low"] - ends["anchor"]), abs(ends["high"] - ends["anchor"]))
    moved = F.col("score") - F.lit(ends["anchor"])
    return derived(kept.select("user_id", (moved / F.lit(size) if size > 0 else moved * 0.0).alias("score")), kept)


class Held:
    """All answers as index arrays, sent out to tasks that make rows of a users x users matrix.

    Users and options are numbered from 0 by id; eight bytes an answer.  What is quadratic is only the
    result, and that is never held: a task makes some rows of it at a time."""

    def __init__(self, responses: DataFrame):
        from ..model import option_dictionary

        book = written(option_dictionary(responses), "options")
        rows = responses.join(book, OPTION).select("user_id", F.col("option_ix").cast("int").alias("o")).toArrow()
        self.ids, user = np.unique(rows.column("user_id").to_numpy(), return_inverse=True)
        option = rows.column("o").to_numpy()
        del rows
        by = np.argsort(user, kind="stable")
        self.option = option[by]
        self.starts = np.append(0, np.cumsum(np.bincount(user, minlength=len(self.ids))))
        self.sizes = np.bincount(option)
        self.choosers = user[np.argsort(option, kind="stable")].astype(np.int32)

    def levels(self) -> list[np.ndarray]:
        """Users by their distance, over shared options, from one at an end; users share options only within a
        level and with the next.  Each component begins a level of its own."""
        first = np.append(0, np.cumsum(self.sizes))

        def lists(starts, values, at):
            n = starts[at + 1] - starts[at]
            return np.unique(values[np.repeat(starts[at] - np.cumsum(n) + n, n) + np.arange(n.sum())])

        def walk(start, seen):
            out, used = [np.array([start])], np.zeros(len(self.sizes), bool)
            seen[start] = True
            while True:
                option = lists(self.starts, self.option, out[-1])
                option = option[~used[option]]
                used[option] = True
                near = lists(first, self.choosers, option)
                near = near[~seen[near]]
                if not len(near):
                    return out
                seen[near] = True
                out.append(near)

        seen, out = np.zeros(len(self.ids), bool), []
        for u in range(len(self.ids)):
            if not seen[u]:
                far = walk(u, seen.copy())
                out += walk(int(far[-1][0]), seen)
        return out

    def reordered(self, order: np.ndarray) -> "Held":
        """The same answers with users numbered in another order."""
        n = np.diff(self.starts)[order]
        out = object.__new__(Held)
        out.ids, out.sizes, out.starts = self.ids[order], self.sizes, np.append(0, np.cumsum(n))
        out.option = self.option[np.repeat(self.starts[order] - out.starts[:-1], n) + np.arange(n.sum())]
        out.choosers = np.repeat(np.arange(len(n), dtype=np.int32), n)[np.argsort(out.option, kind="stable")]
        return out

    def columns(self, most: int = 1 << 24) -> np.ndarray | None:
        """options x users as 0/1, where options are few."""
        m, n = len(self.ids), len(self.sizes)
        if m * n > most:
            return None
        x = np.zeros((n, m))
        x[self.option, np.repeat(np.arange(m), np.diff(self.starts))] = 1
        return x

    def rows(self, lo: int, hi: int, columns: np.ndarray | None, weighted: bool) -> np.ndarray:
        """For users lo .. hi - 1 and each user v the sum over shared options of 1, or of 1 / (n_u n_o) (weighted)."""
        m = len(self.ids)
        option = self.option[self.starts[lo] : self.starts[hi]]
        answers = np.diff(self.starts[lo : hi + 1])
        row = np.repeat(np.arange(hi - lo), answers)
        weight = 1.0 / (answers[row] * self.sizes[option]) if weighted else np.ones(len(option))
        if columns is not None:
            left = np.zeros((hi - lo, len(self.sizes)))
            left[row, option] = weight
            return left @ columns
        n = self.sizes[option]
        before = (np.cumsum(self.sizes) - self.sizes)[option]
        v = self.choosers[np.repeat(before - np.cumsum(n) + n, n) + np.arange(n.sum())]
        return np.bincount(np.repeat(row, n) * m + v, np.repeat(weight, n), (hi - lo) * m).reshape(hi - lo, m)


def narrow_vector(held: Held, weight: np.ndarray, diagonal: np.ndarray, mass: np.ndarray, levels: list[np.ndarray], seed: int, most_rounds: int = 500) -> np.ndarray:
    """The second smallest x of (D - C W C^T) x = t M x, for users in narrow levels: the matrix is block
    tridiagonal by level, its factors take (users x level) cells, and inverse rounds on a few vectors settle
    in a handful of solves however close the eigenvalues are to 0."""
    shift = 1e-9 * float(diagonal.sum() / mass.sum())
    local = np.empty(len(held.ids), np.int64)
    inverse, down, before = [], [], None
    for level in levels:
        local[level] = np.arange(len(level))
        n = held.starts[level + 1] - held.starts[level]
        row = np.repeat(np.arange(len(level)), n)
        option = held.option[np.repeat(held.starts[level] - np.cumsum(n) + n, n) + np.arange(n.sum())]
        names, at = np.unique(option, return_inverse=True)
        c = np.zeros((len(level), len(names)))
        c[row, at] = 1
        own = np.diag(diagonal[level] + shift * mass[level]) - (c * weight[names]) @ c.T
        if before is not None:
            shared, a, b = np.intersect1d(names, before[0], assume_unique=True, return_indices=True)
            link = -(c[:, a] * weight[shared]) @ before[1][:, b].T
            own -= link @ inverse[-1] @ link.T
            down.append(link)
        inverse.append(np.linalg.inv((own + own.T) / 2))
        before = names, c

    def solve(rhs):
        x = [rhs[level] for level in levels]
        for k, link in enumerate(down):
            x[k + 1] = x[k + 1] - link @ (inverse[k] @ x[k])
        x[-1] = inverse[-1] @ x[-1]
        for k in range(len(down) - 1, -1, -1):
            x[k] = inverse[k] @ (x[k] - down[k].T @ x[k + 1])
        out = np.empty_like(rhs)
        for level, part in zip(levels, x):
            out[level] = part
        return out

    m = len(held.ids)
    q, old = np.random.default_rng(seed).standard_normal((m, min(8, max(1, m - 1)))), None
    for _ in range(most_rounds):
        q -= (mass @ q) / mass.sum()
        root = np.sqrt(mass)[:, None]
        q = np.linalg.qr(q * root)[0] / root
        x = solve(mass[:, None] * q)
        x -= (mass @ x) / mass.sum()
        small = (q * mass[:, None]).T @ x  # of the inverse: its largest value is wanted
        values, turn = np.linalg.eigh((small + small.T) / 2)
        q = x @ turn[:, ::-1]
        first = q[:, 0] / np.linalg.norm(q[:, 0])
        if old is not None and min(np.abs(first - old).max(), np.abs(first + old).max()) < 1e-14:
            break
        old = first
    return first


def by_rows(spark, held: Held, make, schema: str, n_rows: int, most_cells: int = 1 << 20) -> DataFrame:
    """make(held, columns, lo, hi) -> arrays of the schema's columns, for all ranges of n_rows rows."""
    import pyarrow as pa

    names = [c.split()[0] for c in schema.split(", ")]
    step = max(1, most_cells // max(1, len(held.ids)))
    sent = spark.sparkContext.broadcast(held)

    def run(batches):
        columns = sent.value.columns()
        for batch in batches:
            at = batch.column(0).to_numpy()
            for lo in range(int(at.min(initial=n_rows)), int(at.max(initial=-1)) + 1, step):
                made = make(sent.value, columns, lo, min(lo + step, int(at.max()) + 1))
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in made], names)

    tasks = min(4096, max(1, n_rows * len(held.ids) >> 22))  # about four million cells each
    return spark.range(0, n_rows, 1, tasks).mapInArrow(run, schema)


def update_matrix(responses: DataFrame) -> DataFrame:
    """u, v, value of the matrix that one averaging round applies; its rows add up to 1.  Quadratic in users."""

    def make(held, columns, lo, hi):
        value = held.rows(lo, hi, columns, True)
        u, v = np.nonzero(value)
        return held.ids[lo + u], held.ids[v], value[u, v]

    held = Held(responses)
    return by_rows(responses.sparkSession, held, make, "u long, v long, value double", len(held.ids))


def positions(responses: DataFrame) -> DataFrame:
    """user_id, pos from 1: the fixed order in which differences are taken."""
    from .rank import global_rank

    return global_rank(responses.select("user_id").distinct(), ["user_id"], "pos")


def to_diffs(scores: DataFrame, pos: DataFrame) -> DataFrame:
    """pos, diff: the next score less this one's; joined by position, with no global window."""
    at = scores.join(pos, "user_id").select("pos", "score")
    after = at.select((F.col("pos") - 1).alias("pos"), F.col("score").alias("after"))
    return at.join(after, "pos").select("pos", (F.col("after") - F.col("score")).alias("diff"))


def from_diffs(diffs: DataFrame, pos: DataFrame, block: int = 100_000) -> DataFrame:
    """user_id, score: running sums from 0 by blocks of positions, each offset by the blocks before."""
    rows = pos.join(diffs.select((F.col("pos") + 1).alias("pos"), "diff"), "pos", "left").select("user_id", "pos", F.coalesce("diff", F.lit(0.0)).alias("diff"), F.floor(F.col("pos") / block).alias("block"))
    rows = written(rows, "diffs")
    totals = rows.groupBy("block").agg(F.sum("diff").alias("total"))
    before = totals.select("block", F.coalesce(F.sum("total").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)).alias("before"))  # one row a block
    within = F.sum("diff").over(Window.partitionBy("block").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0))
    return rows.withColumn("within", within).join(F.broadcast(before), "block").select("user_id", (F.col("within") + F.col("before")).alias("score"))


def difference_rows(held: Held, columns: np.ndarray | None, lo: int, hi: int) -> np.ndarray:
    """Rows lo .. hi - 1 of the matrix that a round applies to differences: sums of the averaging matrix from a
    column on, of the next row less this one."""
    behind = held.rows(lo, hi + 1, columns, True)[:, ::-1].cumsum(1)[:, ::-1]  # the j-th difference moves all users behind position j
    return behind[1:, 1:] - behind[:-1, 1:]


def difference_blocks(held: Held, step: int = 64, most_cells: int = 25_000_000) -> list[tuple[int, int, np.ndarray]]:
    """(first row, first column, cells) of all of the difference matrix but columns in which it is 0: those before
    the users that some rows reach, where both sums are 1, and those behind."""
    blocks, cells, m = [], 0, len(held.ids)
    for lo in range(0, m - 1, step):
        u = held.rows(lo, min(lo + step, m - 1) + 1, None, True)
        reached = np.flatnonzero(u.any(0))
        first, last = int(reached[0]), int(reached[-1])
        behind = u[:, first : last + 1][:, ::-1].cumsum(1)[:, ::-1]
        blocks.append((lo, first, behind[1:, 1:] - behind[:-1, 1:]))
        cells += blocks[-1][2].size
        if cells > most_cells:
            raise SizeGuardError(f"more than {most_cells} cells: the matrix is quadratic; use diffprop_power")
    return blocks


def diff_update_matrix(responses: DataFrame) -> DataFrame:
    """i, j, value of the matrix that one round applies to differences (positions by user_id).

    Entry (i, j): how much of the j-th difference reaches the (i+1)-th less the i-th score.  Quadratic in users.
    """

    def make(held, columns, lo, hi):
        value = difference_rows(held, columns, lo, hi)
        i, j = np.indices(value.shape, np.int64)
        return (i + lo + 1).ravel(), (j + 1).ravel(), value.ravel()

    held = Held(responses)
    return by_rows(responses.sparkSession, held, make, "i long, j long, value double", max(0, len(held.ids) - 1))
