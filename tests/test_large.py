"""Inputs beyond what the quadratic forms held: the whole result, against brute force or the small form."""

from random import Random

import numpy as np
import pytest
from pyspark.sql import functions as F

from abilityrank.model import OPTION, Opts
from abilityrank.operators import consec, dense, fiedler, generate, linalg, metrics, spectral
from abilityrank.operators.rank import rank_users
from abilityrank.plans import workloads
from abilityrank.sources import rsets


def shuffled(spark, m, n):
    """Consistent data of m users whose ids do not follow the order; the true order is r."""
    users = spark.createDataFrame([(int(u), r) for r, u in enumerate(np.random.default_rng(1).permutation(m), 1)], "user_id long, r long")
    data = generate.consistent(users, n).select("user_id", *[F.col(c).cast("string").alias(c) for c in OPTION])
    return users, data.cache()


def test_consecutive_order_agrees_with_the_tree():
    rng, found = Random(5), 0
    for trial in range(1500):
        n = rng.randint(1, 9)
        p = rng.sample(range(n), n)
        runs = [(a, rng.randint(a + 1, n)) for a in (rng.randint(0, n - 1) for _ in range(rng.randint(1, 8)))]
        sets = [frozenset(p[a:b]) for a, b in runs] if trial % 2 else []
        sets += [frozenset(rng.sample(range(n), rng.randint(1, n))) for _ in range(rng.randint(0, 1) if trial % 2 else rng.randint(1, 6))]
        tree = consec.PQTree(list(range(n)))
        ok = all(tree.add(s) for s in sets)
        order = consec.consecutive_order(np.array([x for s in sets for x in s]), np.array([k for k, s in enumerate(sets) for _ in s]), n)
        assert (order is not None) == ok
        if ok:
            found += 1
            at = {u: i for i, u in enumerate(order)}
            assert len(at) == n and all(max(at[u] for u in s) - min(at[u] for u in s) + 1 == len(s) for s in sets)
    assert found > 500


def test_an_order_of_many_users_without_rows_on_the_driver(spark, monkeypatch):
    users, data = shuffled(spark, 3000, 20)
    twin = data.where("user_id < 5").withColumn("user_id", F.col("user_id") + 5000)
    data = data.unionByName(twin)
    data.count()
    monkeypatch.setattr(type(data), "collect", lambda self: pytest.fail("answers as rows on the driver"))
    order = consec.pqtree_order(data)
    monkeypatch.undo()
    assert len(order) == 3005
    assert consec.is_p_matrix(data, spark.createDataFrame([(u, k) for k, u in enumerate(order)], "user_id long, rank long"))
    cycle = data.unionByName(spark.createDataFrame([(int(order[0]), "x", "y"), (int(order[-1]), "x", "y")], data.schema))
    assert consec.pqtree_order(cycle) is None


def answers(spark, m, n_options, seed=2):
    """Each of m users answers three items, with some gaps; ids from 10 on."""
    rng = np.random.default_rng(seed)
    rows = [(10 + u, f"i{i}", f"o{rng.integers(n_options):05d}") for u in range(m) for i in range(3) if i == 0 or rng.random() < 0.8]
    return spark.createDataFrame(rows, "user_id long, item_id string, option_id string").cache(), rows


def one_hot(rows):
    users = {u: k for k, u in enumerate(sorted({r[0] for r in rows}))}
    options = {o: k for k, o in enumerate(sorted({r[1:] for r in rows}))}
    c = np.zeros((len(users), len(options)))
    for u, *o in rows:
        c[users[u], options[tuple(o)]] = 1
    return c


@pytest.mark.parametrize("n_options", [4, 3000])  # with the answers as a matrix, and by lists of choosers
def test_difference_matrix_of_more_than_2000_users(spark, n_options):
    data, rows = answers(spark, 2100, n_options)
    c = one_hot(rows)
    u = (c / c.sum(1, keepdims=True)) @ (c / c.sum(0)).T
    tails = u[:, ::-1].cumsum(1)[:, ::-1]
    found = linalg.diff_update_matrix(data).toArrow()
    got = np.full((2099, 2099), np.nan)
    got[found.column("i").to_numpy() - 1, found.column("j").to_numpy() - 1] = found.column("value").to_numpy()
    assert found.num_rows == 2099**2 and np.allclose(got, tails[1:, 1:] - tails[:-1, 1:])


def test_matrices_of_more_than_20000_users(spark):
    data, _ = answers(spark, 20_100, 30_000)
    right = data.select(F.col("user_id").alias("v"), *OPTION)
    pairs = data.withColumnRenamed("user_id", "u").join(right, OPTION)
    n_u, n_o = data.groupBy(F.col("user_id").alias("u")).agg(F.count("*").alias("nu")), data.groupBy(*OPTION).agg(F.count("*").alias("no"))
    want = {(r["u"], r["v"]): (r["x"], r["n"]) for r in pairs.join(n_u, "u").join(n_o, OPTION).groupBy("u", "v").agg(F.sum(1 / (F.col("nu") * F.col("no"))).alias("x"), F.count("*").alias("n")).collect()}
    got = {(r["u"], r["v"]): r["value"] for r in linalg.update_matrix(data).collect()}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k][0]) < 1e-12 for k in want)
    laplacian = {(r["u"], r["v"]): r["value"] for r in fiedler.laplacian(data).collect()}
    assert {k: -x for k, x in laplacian.items() if k[0] != k[1]} == {k: n for k, (_, n) in want.items() if k[0] != k[1]}
    sums = {}
    for (u, _), x in laplacian.items():
        sums[u] = sums.get(u, 0) + x
    assert not any(sums.values())


@pytest.mark.parametrize(("m", "block"), [(60, 7), (5200, 200_000), (0, 7), (1, 7)])
def test_kendall_with_ties_for_any_number_of_users(spark, m, block):
    rng = np.random.default_rng(6)
    a, b = rng.integers(0, 40, m) / 8.0, rng.integers(0, 9, m).astype(float)
    x, y = (spark.createDataFrame([(i, float(v)) for i, v in enumerate(z)], "user_id long, score double") for z in (a, b))
    got = metrics.kendall_df(x, y, block=block).first()
    sign = np.sign(a[:, None] - a) * np.sign(b[:, None] - b)
    if m < 2:
        assert tuple(got) == (None, None, None)
        return
    nx, ny = (int((z[:, None] != z).sum()) // 2 for z in (a, b))
    c, d = int((sign > 0).sum()) // 2, int((sign < 0).sum()) // 2
    assert (got["concordant"], got["discordant"]) == (c, d) and got["tau"] == pytest.approx((c - d) / (nx * ny) ** 0.5)


def test_sets_beyond_two_million_answers_are_ranked_in_tasks(spark, monkeypatch):
    """Numbered sets give what groups of answers gave, at any number of answers, also in chunks."""
    sf = "/root/testdata/sf0.001"
    sets, methods = ("R1", "R6"), (*workloads.UNPRIVILEGED, "majority_agreement")
    data = [rsets.rset(spark, sf, n).withColumn("run", F.lit(i)) for i, n in enumerate(sets)]
    data = data[0].unionByName(data[1]).cache()
    by = ["run", "method", "user_id"]
    want = workloads.scores_of_runs(data, 2, methods).toPandas().sort_values(by).reset_index(drop=True)
    made = workloads.solved(workloads.packed(data), 2, methods, workloads._by_user, workloads.SCORES_BY_USER).toPandas().sort_values(by).reset_index(drop=True)
    assert (made[[*by, "n_users", "n_items"]] == want[[*by, "n_users", "n_items"]]).all(axis=None)
    assert np.allclose(made["score"], want["score"], rtol=1e-6, atol=1e-9)
    monkeypatch.setattr(dense, "MOST_ANSWERS", 10)
    monkeypatch.setattr(workloads, "method_scores", lambda *a: pytest.fail("rounds over frames"))
    found = workloads.without_truth(spark, sf, sets).toPandas()
    assert len(found) == 18 and found["value"].notna().sum() >= 12
    a = dense.Answers(np.arange(5), np.arange(9, dtype=np.int32) % 5, np.arange(9, dtype=np.int32) % 4, np.array([0, 0, 1, 1]))
    up, down = a.up(np.arange(5.0)), a.down(np.arange(4.0))
    monkeypatch.setattr(dense, "CHUNK", 2)
    assert (a.up(np.arange(5.0)) == up).all() and (a.down(np.arange(4.0)) == down).all()
    assert up.tolist() == [0 + 4 + 3, 1 + 0, 2 + 1, 3 + 2]


def test_sums_by_lists_equal_sums_by_answer(monkeypatch):
    """Answers in any order, users and options without answers, lists cut by a chunk's end."""
    rng = np.random.default_rng(3)
    for trial in range(60):
        m, n, k = rng.integers(1, 9, 3)
        user, option = rng.integers(0, m, 6 * k).astype(np.int32), rng.integers(0, n, 6 * k).astype(np.int32)
        if trial % 2:
            user.sort()
        a = dense.Answers(np.arange(m), user, option, np.arange(n))
        monkeypatch.setattr(dense, "CHUNK", int(rng.integers(1, 12)))
        monkeypatch.setattr(dense, "SUMMED", int(rng.integers(1, 12)))
        s, w = rng.integers(-9, 9, m).astype(float), rng.integers(-9, 9, n).astype(float)
        assert (a.up(s) == np.bincount(option, s[user], n)).all() and (a.down(w) == np.bincount(user, w[option], m)).all()
        assert (a.size == np.bincount(option, minlength=n)).all() and (a.degree == np.bincount(user, minlength=m)).all()
        assert a.choosers.members.dtype == np.int32
    none = dense.Answers(np.arange(2), np.zeros(0, np.int32), np.zeros(0, np.int32), np.arange(3))
    assert none.up(np.ones(2)).tolist() == [0, 0, 0] and none.down(np.ones(3)).tolist() == [0, 0]


def test_users_who_answer_alike_have_equal_sums(spark, monkeypatch):
    """To the last bit, whatever order their answers come in and wherever chunks end."""
    rng = np.random.default_rng(8)
    rows = [(u, f"i{i:02d}", "x") for u in range(12) for i in rng.permutation(25)]
    packed = workloads.packed(spark.createDataFrame(rows, "user_id long, item_id string, option_id string").withColumn("run", F.lit(0)))
    monkeypatch.setattr(dense, "SUMMED", 40)
    _, a, _ = next(dense.packed_sets(packed.sortWithinPartitions("run", "user_id").coalesce(1).toArrow().select(["run", "user_id", "theta", "codes"]).to_batches()))
    assert len(set(a.down(rng.random(25) * 1e6).tolist())) == 1


def test_document_counts_take_whole_texts(spark):
    """Counts by runs and by what is taken off equal those of single characters, also in broken UTF-8."""
    text = F.coalesce("text", F.lit(""))
    made = [("",), ("a\n\r\nB1 \u00e9\u6f22\U0001f600 \x00\x7f\x85 ,;#|",), ("\n\n",), (" ",), ("\U0001f600\U0001f60012",), (None,)]
    broken = spark.sql("select cast(X'41FF31C328' as string) as text union all select cast(X'EDA08031F09F' as string)")
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("text").unionByName(spark.createDataFrame(made, "text string")).unionByName(broken)
    single = {"letters": "[^a-zA-Z]", "digits": "[^0-9]", "capitals": "[^A-Z]", "lines": "[^\n]", "marks": "[^.,;:!?]", "symbols": "[^#*$%&|<>]", "blanks": "[^ ]", "wide": "[\\x00-\\x7F]"}
    counts = rsets._doc_counts(text)
    want = {k: F.length(F.regexp_replace(text, p, "")) + int(k == "lines") for k, p in single.items()} | {"chars": F.length(text)}
    assert set(counts) == set(want)
    assert sum(docs.select(*[F.sum((counts[k] != want[k]).cast("int")).alias(k) for k in want]).first()) == 0


def test_sets_by_size_give_the_same_scores(spark):
    """Tasks of larger sets begin first; what comes out does not depend on it."""
    data = [rsets.rset(spark, "/root/testdata/sf0.001", n).withColumn("run", F.lit(i)) for i, n in enumerate(("R1", "R6"))]
    sets = workloads.packed(data[0].unionByName(data[1]))
    a, b = (sorted(map(tuple, workloads.solved(sets, 2, ("hits", "majority_agreement"), workloads._by_user, workloads.SCORES_BY_USER, sizes).collect())) for sizes in (None, (1, 2)))
    assert a == b and {r[0] for r in a} == {0, 1}


@pytest.mark.parametrize("direct", [spectral.diffprop_direct, fiedler.fiedler_direct])
def test_direct_variants_of_more_than_5000_users(spark, direct):
    users, data = shuffled(spark, 5200, 10)
    scores = direct(data).scores
    assert abs(metrics.spearman(scores, users.withColumnRenamed("r", "score"))) == pytest.approx(1.0, abs=1e-12)
    assert consec.is_p_matrix(data, rank_users(scores))


@pytest.mark.parametrize("direct", [spectral.diffprop_direct, fiedler.fiedler_direct])
def test_factors_by_levels_give_the_dense_vector(spark, direct):
    """Gaps in the answers and unequal options; two components as well as one."""
    _, data = shuffled(spark, 300, 6)
    data = data.where("pmod(xxhash64(user_id, item_id), 11) > 0").cache()
    want = np.array([r["score"] for r in direct(data).scores.orderBy("user_id").collect()])
    got = np.array([r["score"] for r in direct(data, Opts(max_users=290)).scores.orderBy("user_id").collect()])
    assert min(np.abs(got - want).max(), np.abs(got + want).max()) < 1e-8
    apart = data.unionByName(data.withColumn("user_id", F.col("user_id") + 1000).withColumn("item_id", F.concat(F.lit("x"), "item_id")))
    held = linalg.Held(apart)
    assert sorted(np.concatenate(held.levels()).tolist()) == list(range(600))
    assert direct(apart, Opts(max_users=500)).scores.where("score is null or isnan(score)").count() == 0


def test_naive_variant_of_more_than_2000_users(spark):
    """To its tolerance, which takes more than the usual thousand rounds."""
    users, data = shuffled(spark, 2100, 20)
    found = spectral.diffprop_naive(data, Opts(tol=1e-7, max_iter=1_000_000))
    assert found.rounds > 1000 and found.trace[-1]["iter"] <= found.rounds and len(found.trace) < 2000
    assert abs(metrics.spearman(found.scores, users.withColumnRenamed("r", "score"))) == pytest.approx(1.0, abs=1e-12)
    held = linalg.Held(data.where("user_id < 60"))
    full = np.zeros((59, 59))
    for lo, first, cells in linalg.difference_blocks(held, 7):
        full[lo : lo + len(cells), first : first + cells.shape[1]] = cells
    assert np.allclose(full, linalg.difference_rows(held, held.columns(), 0, 59), atol=1e-14)


def test_cost_model_reads_its_table(spark):
    from abilityrank.queries import QUERIES

    sf = "/root/testdata/sf0.01"
    stats = rsets.rset(spark, sf, "R1").agg(F.countDistinct("user_id").alias("m"), F.countDistinct("item_id").alias("n")).first()
    df = QUERIES["cost_model"](spark, sf)
    assert {tuple(r) for r in df.collect()} == {("diffprop_power", 20.0 * stats["m"] * stats["n"]), ("fiedler_direct", float(stats["m"] ** 2 * stats["n"]))}
    assert df.columns == ["method", "steps"] and len(df.inputFiles()) > 0
