"""Every method on one bounded data set held as index arrays.

A worker runs these when many small data sets are ranked at once (experiments, the SQL table
function): one group of answers in, scores out.  They are the same methods as the DataFrame ones,
with the same tolerances; tests hold the two against each other.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pandas as pd

from ..model import SizeGuardError

MOST_ANSWERS = 2_000_000
#: Of a set that comes in numbered (``packed``): twelve bytes an answer, so 600 MB.
MOST_PACKED = 50_000_000
CHUNK = 1 << 22
#: Answers that are summed at once: what they need stays in a core's cache.
SUMMED = 1 << 16
MOST_DENSE_USERS = 2_000
TOLERANCE, MOST_ROUNDS = 1e-5, 1_000


@dataclass
class Answers:
    """user, option: one entry an answer; users in id order, options in item and option order."""

    users: np.ndarray
    user: np.ndarray
    option: np.ndarray
    item_of: np.ndarray

    @classmethod
    def of(cls, user, item, option) -> "Answers":
        if len(user) > MOST_ANSWERS:
            raise SizeGuardError("too many answers for one data set: use the DataFrame API")
        users, user = np.unique(np.asarray(user), return_inverse=True)
        _, item = np.unique(np.asarray(item), return_inverse=True)
        _, name = np.unique(np.asarray(option), return_inverse=True)
        pairs, option = np.unique(item.astype(np.int64) * (int(name.max(initial=0)) + 1) + name, return_inverse=True)
        return cls(users, user, option, pairs // (int(name.max(initial=0)) + 1))

    @property
    def degree(self) -> np.ndarray:
        return _counts(self.user, len(self.users)).astype(float)

    @property
    def size(self) -> np.ndarray:
        return _counts(self.option, len(self.item_of)).astype(float)

    @cached_property
    def choosers(self) -> "Lists":
        return Lists.of(self.option, self.user, len(self.item_of))

    @cached_property
    def picks(self) -> "Lists":
        return Lists.of(self.user, self.option, len(self.users))

    def up(self, scores: np.ndarray) -> np.ndarray:
        """Sums of user scores by option."""
        return self.choosers.sums(scores)

    def down(self, weights: np.ndarray) -> np.ndarray:
        """Sums of option weights by user."""
        return self.picks.sums(weights)

    def matrix(self) -> np.ndarray:
        if len(self.users) > MOST_DENSE_USERS:
            raise SizeGuardError(f"{len(self.users)} users: the matrix is quadratic; use the power variant")
        c = np.zeros((len(self.users), len(self.item_of)))
        c[self.user, self.option] = 1
        return c


def _counts(of: np.ndarray, n: int) -> np.ndarray:
    """How often each of 0 .. n - 1 occurs, some at a time: indexes are widened to count them."""
    total = np.zeros(n, np.int64)
    for lo in range(0, len(of), CHUNK):
        total += np.bincount(of[lo : lo + CHUNK], minlength=n)
    return total


@dataclass
class Lists:
    """``members`` of the keys ``at``, one list after the other; ``starts`` where each begins."""

    n: int
    at: np.ndarray
    starts: np.ndarray
    members: np.ndarray

    @classmethod
    def of(cls, key: np.ndarray, member: np.ndarray, n: int) -> "Lists":
        counts = _counts(key, n)
        at = np.flatnonzero(counts)
        starts = np.cumsum(counts) - counts
        if (key[1:] >= key[:-1]).all():
            return cls(n, at, starts[at], member)
        members, place = np.empty_like(member), starts.copy()
        for lo in range(0, len(key), CHUNK):
            own = key[lo : lo + CHUNK]
            order = np.argsort(own, kind="stable")
            own, new = own[order], np.bincount(own, minlength=n)
            members[(place - np.cumsum(new) + new)[own] + np.arange(len(own))] = member[lo : lo + CHUNK][order]
            place += new
        return cls(n, at, starts[at], members)

    def sums(self, values: np.ndarray) -> np.ndarray:
        """Sums of the members' values by key; only lists longer than ``SUMMED`` are cut, so equal lists have
        equal sums."""
        total, lo = np.zeros(self.n), 0
        while lo < len(self.members):
            first, end = np.searchsorted(self.starts, lo, "right") - 1, np.searchsorted(self.starts, lo + SUMMED, "right") - 1
            hi = int(self.starts[end]) if end > first and lo + SUMMED < len(self.members) else lo + SUMMED
            own = values.take(self.members[lo:hi])
            end = np.searchsorted(self.starts, lo + len(own))
            total[self.at[first:end]] += np.add.reduceat(own, np.maximum(self.starts[first:end] - lo, 0))
            lo = hi
        return total


def packed_sets(batches):
    """(first columns' values, Answers, theta by user) of each set in batches of rows (.., user_id, theta, codes)
    that come by set and user; codes are item << 31 | option, numbered in item and option order."""
    held, now = [], None
    item_at = np.zeros(0, np.int32)

    def made():
        users, theta, counts, option = (np.concatenate(x) for x in zip(*held))
        held.clear()
        low, high = int(option.min()), int(option.max())
        option -= low
        _, item_of = np.unique(item_at[low : high + 1], return_inverse=True)
        return now, Answers(users, np.repeat(np.arange(len(users), dtype=np.int32), counts), option, item_of), theta

    for batch in batches:
        names = [c.to_pylist() for c in batch.columns[:-3]]
        keys = list(zip(*names))
        users, theta = batch.column(len(names)).to_numpy(), batch.column(len(names) + 1).to_numpy(zero_copy_only=False).astype(float)
        counts = batch.column(len(names) + 2).value_lengths().to_numpy()
        codes, ends = batch.column(len(names) + 2).flatten().to_numpy(), np.append(0, np.cumsum(counts))
        cuts = [0, *(i for i in range(1, len(keys)) if keys[i] != keys[i - 1]), len(keys)]
        for lo, hi in zip(cuts, cuts[1:]):
            if lo == hi:
                continue
            if held and keys[lo] != now:
                yield made()
            now = keys[lo]
            own = codes[ends[lo] : ends[hi]]
            option = (own & ((1 << 31) - 1)).astype(np.int32)
            if option.max() >= len(item_at):
                item_at = np.append(item_at, np.zeros(2 * int(option.max()) + 1 - len(item_at), np.int32))
            item_at[option] = own >> 31
            held.append((users[lo:hi], theta[lo:hi], counts[lo:hi], option))
    if held:
        yield made()


def _unit_diff(s: np.ndarray) -> tuple[np.ndarray, float]:
    d = np.diff(s)
    norm = float(np.linalg.norm(d))
    return (d / norm if norm else d), norm


def _seriate(a: Answers, step, seed: int, rounds: int | None) -> np.ndarray:
    """Power rounds with the first user at 0, until the unit differences stand still."""
    s, old = np.random.default_rng(seed).random(len(a.users)), None
    for _ in range(rounds if rounds is not None else MOST_ROUNDS):
        s = step(s)
        s = s - s[0]
        d, norm = _unit_diff(s)
        if not norm:
            break
        s = s / norm
        if rounds is None and old is not None and np.linalg.norm(d - old) < TOLERANCE:
            break
        old = d
    return s


def diffprop(a: Answers, seed: int = 42, rounds: int | None = None) -> np.ndarray:
    degree, size = a.degree, a.size
    return _seriate(a, lambda s: a.down(a.up(s) / size) / degree, seed, rounds)


def diffprop_direct(a: Answers) -> np.ndarray:
    root = np.sqrt(a.degree)
    half = a.matrix() / root[:, None]
    return np.linalg.eigh((half / a.size) @ half.T)[1][:, max(0, len(root) - 2)] / root


def fiedler(a: Answers, seed: int = 42) -> np.ndarray:
    """Direct for few users, power rounds for more: the same vector."""
    d = a.down(a.size)
    if len(a.users) <= MOST_DENSE_USERS:
        c = a.matrix()
        return np.linalg.eigh(np.diag(d) - c @ c.T)[1][:, min(1, len(d) - 1)]
    beta = 2.0 * d.max(initial=0.0)
    return _seriate(a, lambda s: (beta - d) * s + a.down(a.up(s)), seed, None)


def _settled(s: np.ndarray, step, rounds: int | None = None) -> np.ndarray:
    for _ in range(rounds or MOST_ROUNDS):
        new = step(s)
        change, s = np.linalg.norm(new - s), new
        if rounds is None and change < TOLERANCE:
            break
    return s


def hits(a: Answers, rounds: int | None = None) -> np.ndarray:
    def step(s):
        s = a.down(a.up(s))
        return s / (np.linalg.norm(s) or 1.0)

    return _settled(np.ones(len(a.users)), step, rounds)


def truthfinder(a: Answers, rounds: int | None = None) -> np.ndarray:
    """Mean log-odds of the options picked, by the trust that the rounds settle on: the order of trust,
    without its ties where beliefs round to 1."""
    degree = a.degree
    miss = lambda s: a.up(np.log(np.maximum(1 - s, 1e-12)))
    s = _settled(np.full(len(a.users), 0.9), lambda s: a.down(1 - np.exp(miss(s))) / degree, rounds)
    return a.down(-miss(s)) / degree


def _invested(a: Answers, power: float, pooled: bool, rounds: int = 10) -> np.ndarray:
    degree, items = a.degree, int(a.item_of.max(initial=-1)) + 1

    def step(s):
        stake = s / degree
        invested = a.up(stake)
        grown = invested**power
        value = grown
        if pooled:
            total = np.bincount(a.item_of, grown, items)[a.item_of]
            value = np.divide(invested * grown, total, out=np.zeros_like(grown), where=total > 0)
        share = np.divide(value, invested, out=np.zeros_like(value), where=invested > 0)
        s = a.down(share) * stake
        return s / (s.max(initial=0.0) or 1.0)

    return _settled(np.ones(len(a.users)), step, rounds)


def investment(a: Answers) -> np.ndarray:
    return _invested(a, 1.2, False)


def pooled_investment(a: Answers) -> np.ndarray:
    return _invested(a, 1.4, True)


def participation(a: Answers) -> np.ndarray:
    return a.degree


def descending(a: Answers, scores: np.ndarray) -> np.ndarray:
    """Ranks from 1; equal scores (to nine digits) by user."""
    order = np.lexsort((np.arange(len(scores)), -np.round(scores, 9)))
    rank = np.empty(len(scores), np.int64)
    rank[order] = np.arange(1, len(scores) + 1)
    return rank


def slice_entropy(a: Answers, inside: np.ndarray) -> float | None:
    """Mean entropy, over the items answered there, of the answers of some users."""
    counts = np.bincount(a.option[inside[a.user]], minlength=len(a.item_of)).astype(float)
    total = np.bincount(a.item_of, counts)
    share = np.divide(counts, total[a.item_of], out=np.zeros_like(counts), where=total[a.item_of] > 0)
    h = -np.bincount(a.item_of, np.where(share > 0, share * np.log(np.where(share > 0, share, 1)), 0))
    return float(h[total > 0].mean()) if (total > 0).any() else None


def oriented(a: Answers, scores: np.ndarray, share: float = 0.1) -> np.ndarray:
    """The able end high: the one whose answers agree more; slices that tie are widened."""
    rank, m = descending(a, scores), len(scores)
    while m:
        size = max(1, int(np.ceil(m * share)))
        top, bottom = slice_entropy(a, rank <= size), slice_entropy(a, rank > m - size)
        if top is not None and bottom is not None and abs(top - bottom) > 1e-12:
            return scores if top < bottom else -scores
        if share >= 0.5:
            break
        share = min(0.5, share * 2)
    return scores


def is_consecutive(a: Answers, rank: np.ndarray) -> bool:
    """Whether each option's choosers stand together in the order."""
    low = np.full(len(a.item_of), len(rank) + 1)
    high = np.zeros(len(a.item_of))
    np.minimum.at(low, a.option, rank[a.user])
    np.maximum.at(high, a.option, rank[a.user])
    return bool((high - low + 1 == a.size).all())


def majority(a: Answers) -> np.ndarray:
    """Options that are their item's most frequent one, the first among equals."""
    order = np.lexsort((np.arange(len(a.item_of)), -a.size, a.item_of))
    first = np.append(True, a.item_of[order][1:] != a.item_of[order][:-1])[: len(order)]
    out = np.zeros(len(a.item_of), bool)
    out[order[first]] = True
    return out


UNPRIVILEGED = {
    "diffprop": lambda a: oriented(a, diffprop(a)), "diffprop_direct": lambda a: oriented(a, diffprop_direct(a)), "fiedler": lambda a: oriented(a, fiedler(a)),
    "hits": hits, "truthfinder": truthfinder, "investment": investment, "pooled_investment": pooled_investment, "participation": participation,
}


def scores(a: Answers, method: str, correct: np.ndarray | None = None, grade: np.ndarray | None = None) -> np.ndarray:
    """``correct`` and ``grade`` (0 worst) of each answer: only the methods that are told them use them."""
    if method == "true_answer":
        return np.bincount(a.user, correct, len(a.users))
    if method == "majority_agreement":
        return a.down(majority(a).astype(float))
    if method == "graded_estimator":
        from .privileged import abilities

        _, item = np.unique(a.item_of[a.option], return_inverse=True)
        return abilities(a.user, item, np.asarray(grade))
    if method not in UNPRIVILEGED:
        raise ValueError(f"method: one of {', '.join((*UNPRIVILEGED, 'true_answer', 'majority_agreement', 'graded_estimator'))}")
    return UNPRIVILEGED[method](a)


def average_ranks(x: np.ndarray) -> np.ndarray:
    return pd.Series(np.round(x, 9)).rank(method="average").to_numpy()


def spearman(x: np.ndarray, y: np.ndarray) -> float | None:
    """None where one side is constant or holds what is no number."""
    if len(x) < 2 or not (np.isfinite(x).all() and np.isfinite(y).all()):
        return None
    x, y = average_ranks(x), average_ranks(y)
    spread = x.std() * y.std()
    return float(((x - x.mean()) * (y - y.mean())).mean() / spread) if spread > 0 else None
