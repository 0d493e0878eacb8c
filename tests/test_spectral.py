import numpy as np
import pytest
from pyspark.sql import functions as F

from abilityrank.model import Opts, SizeGuardError
from abilityrank.operators import consec, fiedler, generate, linalg, metrics, orient, spectral
from abilityrank.operators.rank import global_rank, rank_users

from fixtures import CYCLE, SCHEMA, order_of, path_data

OLD = np.array([[22, 10, 4, 0], [10, 16, 10, 0], [4, 10, 16, 6], [0, 0, 6, 30]]) / 36


def dense(df, i, j, n):
    m = np.zeros((n, n))
    for r in df.collect():
        m[r[i] - 1, r[j] - 1] = r["value"]
    return m


def test_update_matrices(spark):
    r = path_data(spark)
    u = dense(linalg.update_matrix(r), "u", "v", 4)
    assert np.allclose(u, OLD) and np.allclose(u.sum(1), 1)
    d = dense(linalg.diff_update_matrix(r), "i", "j", 3)
    assert np.allclose(d * 36, [[12, 6, 0], [6, 12, 6], [4, 14, 24]])
    assert np.allclose(sorted(np.linalg.eigvals(d).real), [0.114535, 0.390311, 0.828487], atol=1e-6)


def test_laplacian(spark):
    want = [[3, -2, -1, 0], [-2, 4, -2, 0], [-1, -2, 4, -1], [0, 0, -1, 1]]
    assert np.allclose(dense(fiedler.laplacian(path_data(spark)), "u", "v", 4), want)


def test_differences_round_trip(spark):
    r = path_data(spark)
    pos = linalg.positions(r)
    scores = spark.createDataFrame([(1, 3.0), (2, 5.0), (3, 4.0), (4, 9.0)], "user_id long, score double")
    back = linalg.from_diffs(linalg.to_diffs(scores, pos), pos, block=2)
    assert [(x["user_id"], x["score"]) for x in back.orderBy("user_id").collect()] == [(1, 0.0), (2, 2.0), (3, 1.0), (4, 6.0)]


@pytest.mark.parametrize("run", [
    lambda r: spectral.diffprop_power(r, Opts(path="gram", tol=1e-9)), lambda r: spectral.diffprop_power(r, Opts(path="arrow", tol=1e-4)), lambda r: spectral.diffprop_power(r, Opts(path="sql", rounds=8)),
    lambda r: spectral.diffprop_power(r, Opts(path="sql", rounds=4), step="diff"), lambda r: spectral.diffprop_direct(r), lambda r: spectral.diffprop_naive(r, Opts(tol=1e-8)),
    lambda r: spectral.diffprop_deflation(r, Opts(rounds=8)), lambda r: spectral.diffprop_deflation(r, Opts(rounds=6), left="iterate"), lambda r: spectral.diffprop_deflation(r, scheme="symmetrised"),
    lambda r: fiedler.fiedler_direct(r), lambda r: fiedler.fiedler_direct(r, solver="lanczos"), lambda r: fiedler.fiedler_power(r, Opts(rounds=12)),
])
def test_every_variant_finds_the_order(spark, run):
    assert order_of(run(path_data(spark)).scores) == [1, 2, 3, 4]


def test_scores_are_the_second_eigenvector(spark):
    got = {r["user_id"]: r["score"] for r in spectral.diffprop_power(path_data(spark), Opts(path="gram", tol=1e-12)).scores.collect()}
    want = np.array([0, 0.118612, 0.471001, 1.399308]) / 1.399308
    assert np.allclose(np.abs([got[i] for i in (1, 2, 3, 4)]), want, atol=1e-5)


def test_left_vector_is_the_number_of_answers(spark):
    r = path_data(spark).where("not (user_id = 2 and item_id = 't3')")
    got = [x["score"] for x in spectral.left_vector(r, Opts(rounds=25)).orderBy("user_id").collect()]
    assert np.allclose(got, np.array([3, 2, 3, 3]) / 11, atol=1e-3)


def test_guards_and_wrong_options(spark):
    r = path_data(spark)
    with pytest.raises(SizeGuardError):
        spectral.diffprop_direct(r, Opts(max_users=3))
    with pytest.raises(ValueError):
        spectral.diffprop_deflation(r, scheme="symmetric")
    with pytest.raises(ValueError):
        spectral.diffprop_power(r, step="other")


def test_averaging_collapses(spark):
    spread = spectral.avghits(path_data(spark), Opts(rounds=60)).scores.agg(F.max("score") - F.min("score")).first()[0]
    assert spread < 1e-3


def test_equal_orders_of_the_worked_example(spark):
    def order(*v):
        return [r["rank"] for r in rank_users(spark.createDataFrame(list(enumerate(v, 1)), "user_id long, score double")).orderBy("user_id").collect()]

    assert order(0.36, 0.8, 0.48) == order(0.48, 0.64, 0.6) == [3, 1, 2]


def test_ties(spark):
    s = spark.createDataFrame([(1, 1.0), (2, 1.0), (3, 0.0)], "user_id long, score double")
    assert {r["user_id"]: r["rank"] for r in rank_users(s, ties="average").collect()} == {1: 1.5, 2: 1.5, 3: 3.0}
    assert {r["user_id"]: r["rank"] for r in rank_users(s, ties="min").collect()} == {1: 1, 2: 1, 3: 3}


def test_global_rank_over_partitions(spark):
    df = spark.range(1000).select(((F.col("id") * 7919) % 1009).alias("x"))
    ranked = global_rank(df, ["x"], "k", partitions=7).orderBy("x").collect()
    assert [r["k"] for r in ranked] == list(range(1, 1001))


def test_consistent_data_is_recovered_exactly(spark):
    users = spark.range(1, 31).select(F.col("id").alias("user_id"), F.col("id").alias("r"))
    data = generate.consistent(users, 10).select("user_id", F.col("item_id").cast("string"), F.col("option_id").cast("string")).cache()
    truth = users.select("user_id", F.col("r").alias("score"))
    for scores in (spectral.diffprop_direct(data).scores, fiedler.fiedler_direct(data).scores, spectral.diffprop_power(data, Opts(tol=1e-9)).scores):
        assert abs(metrics.spearman(scores, truth)) == pytest.approx(1.0)
        assert consec.is_p_matrix(data, rank_users(scores))


def test_consecutive_orders(spark):
    r = path_data(spark)
    assert sorted(consec.co_orders_bruteforce(r)) == [(1, 2, 3, 4), (4, 3, 2, 1)]
    assert consec.pqtree_order(r) in ([1, 2, 3, 4], [4, 3, 2, 1])
    cycle = spark.createDataFrame(CYCLE, SCHEMA)
    assert consec.pqtree_order(cycle) is None and consec.co_orders_bruteforce(cycle) == []
    assert not consec.is_consistent(cycle) and consec.is_consistent(r, "fiedler")


def test_pqtree_agrees_with_brute_force():
    from itertools import permutations
    from random import Random

    rng = Random(4)
    for _ in range(400):
        n = rng.randint(2, 6)
        sets = [frozenset(rng.sample(range(n), rng.randint(1, n))) for _ in range(rng.randint(1, 5))]

        def good(p):
            at = {u: i for i, u in enumerate(p)}
            return all(max(at[u] for u in s) - min(at[u] for u in s) + 1 == len(s) for s in sets)

        tree = consec.PQTree(list(range(n)))
        ok = all(tree.add(s) for s in sets)
        assert ok == any(good(p) for p in permutations(range(n)))
        assert not ok or good(tree.root.frontier())


def test_orientation_prefers_agreement(spark):
    scores = spark.createDataFrame([(1, 0.0), (2, 0.1), (3, 0.5), (4, 1.4)], "user_id long, score double")
    kept, how = orient.orient_by_entropy(path_data(spark), scores)
    assert how == "reversed"  # users 1 and 2 agree more
    assert order_of(kept) == [1, 2, 3, 4] and kept.where("user_id = 1").first()["score"] > kept.where("user_id = 4").first()["score"]


def test_spearman_and_kendall_match_counts(spark):
    rng = np.random.default_rng(3)
    a, b = rng.permutation(50), rng.permutation(50)
    x = spark.createDataFrame([(i, float(v)) for i, v in enumerate(a)], "user_id long, score double")
    y = spark.createDataFrame([(i, float(v)) for i, v in enumerate(b)], "user_id long, score double")
    assert metrics.spearman(x, y) == pytest.approx(np.corrcoef(a, b)[0, 1])
    tau = sum(np.sign(a[i] - a[j]) * np.sign(b[i] - b[j]) for i in range(50) for j in range(i)) / (50 * 49 / 2)
    assert metrics.kendall_df(x, y).first()["tau"] == pytest.approx(tau)
    assert metrics.kendall_large(x, y, block=7) == pytest.approx(tau)
