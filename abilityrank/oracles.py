"""The registered queries' results as DuckDB SQL over the same tables."""

from __future__ import annotations

ROUNDS = 20


def draw(*parts: str) -> str:
    """The uniform draw of ``functions.draws``."""
    return f"(('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, 13))::BIGINT / 4503599627370496.0)"


def _latest(user: str, item: str, option: str, source: str, order: str) -> str:
    return f"SELECT user_id, item_id, option_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id, item_id ORDER BY {order}) AS n FROM (SELECT {user}::BIGINT AS user_id, ({item})::VARCHAR AS item_id, ({option})::VARCHAR AS option_id, x.* FROM ({source}) x)) WHERE n = 1"


def _features() -> str:
    from .sources.rsets import FEATURES

    patterns = {"letters": "[^a-zA-Z]", "digits": "[^0-9]", "capitals": "[^A-Z]", "lines": r"[^\n]", "marks": "[^.,;:!?]", "symbols": "[^#*$%&|<>]", "blanks": "[^ ]", "wide": r"[\x00-\x7F]"}
    counts = ", ".join(f"length(regexp_replace(t, '{p}', '', 'g')){' + 1' if n == 'lines' else ''} AS {n}" for n, p in patterns.items())
    bins = " UNION ALL ".join(f"SELECT doc_id AS user_id, '{n}' AS item_id, ({' + '.join(f'({n} >= {c})::INT' if over is None else f'(1000 * {n} >= {c} * {over})::INT' for c in cuts)})::VARCHAR AS option_id FROM c" for n, over, cuts in FEATURES)
    return f"WITH c AS MATERIALIZED (SELECT doc_id::BIGINT AS doc_id, lang, length(t) AS chars, {counts} FROM (SELECT doc_id, coalesce(lang, 'none') AS lang, coalesce(text, '') AS t FROM documents)) {bins} UNION ALL SELECT doc_id, 'lang', lang FROM c"


R = {
    "R1": _latest("l_suppkey", "p_brand", "l_returnflag", "SELECT l_suppkey, l_returnflag, l_shipdate, l_orderkey, l_linenumber, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey", "l_shipdate DESC, l_orderkey DESC, l_linenumber DESC, option_id DESC"),
    "R2": _latest("l_suppkey", "l_partkey", "l_returnflag", "SELECT l_suppkey, l_partkey, l_returnflag, l_shipdate, l_orderkey, l_linenumber FROM lineitem", "l_shipdate DESC, l_orderkey DESC, l_linenumber DESC, option_id DESC"),
    "R3": _latest("o_custkey", "year(o_orderdate)::VARCHAR || 'Q' || quarter(o_orderdate)::VARCHAR", "o_orderpriority", "SELECT o_custkey, o_orderdate, o_orderpriority, o_orderkey FROM orders", "o_orderdate DESC, o_orderkey DESC"),
    "R4": _latest("u", "ts::DATE", "event_type", "SELECT user_id AS u, ts, event_type, event_id FROM events", "ts DESC, event_id DESC"),
    "R5": "SELECT vec_id::BIGINT AS user_id, dim::VARCHAR AS item_id, (ntile(3) OVER (PARTITION BY dim ORDER BY x, vec_id))::VARCHAR AS option_id FROM (SELECT vec_id, unnest(embedding) AS x, unnest(range(len(embedding))) AS dim FROM embeddings)",
    "R6": _features(),
    "R7": "SELECT conv_id::BIGINT AS user_id, turn::VARCHAR AS item_id, role || ':' || (length(text) // 100)::VARCHAR AS option_id FROM conversations",
}

_THETA = "SELECT s_suppkey::BIGINT AS user_id, (s_acctbal - min(s_acctbal) OVER ()) / (max(s_acctbal) OVER () - min(s_acctbal) OVER ()) AS theta FROM supplier"


def _list(tag: str, n: int, scale: str, shift: str = "0") -> str:
    return "[" + ", ".join(f"{draw('item_id', repr(tag), str(h), '42')} * {scale} + {shift}" for h in range(n)) + "]"


_ITEMS = f"SELECT item_id, {draw('item_id', repr('a'), '42')} * 10.0 AS a, {_list('s', 3, '10.0')} AS s, {_list('b', 3, '1.0', '-0.5')} AS b, {_list('t', 2, '1.0', '-0.5')} AS t FROM (SELECT p_partkey::BIGINT AS item_id FROM part WHERE p_partkey <= 50)"
_PAIRS = f"SELECT *, {draw('user_id', 'item_id', '42')} AS u FROM ({_THETA}), ({_ITEMS})"
_SIGMA = "1.0 / (1.0 + exp(-(a * (theta - {b}))))"


def _nominal(extra: str) -> str:
    w = ", ".join(f"exp(s[{h}] * (theta - b[{h}])) AS w{h}" for h in (1, 2, 3))
    if extra:
        p = [f"(w{h} + 1.0 / 3) / (((w1 + w2) + w3) + 1.0)" for h in (1, 2, 3)]
    else:
        p = [f"w{h} / ((w1 + w2) + w3)" for h in (1, 2, 3)]
    return f"SELECT user_id, item_id, least(2, (u >= {p[0]})::INT + (u >= {p[0]} + {p[1]})::INT + (u >= {p[0]} + {p[1]} + {p[2]})::INT)::INT AS option_id FROM (SELECT user_id, item_id, u, {w} FROM ({_PAIRS}))"


_GRADED = f"SELECT user_id, item_id, ((u < {_SIGMA.format(b='t[1]')})::INT + (u < {_SIGMA.format(b='t[2]')})::INT)::INT AS option_id FROM ({_PAIRS})"
_CONSISTENT = "SELECT user_id, i::BIGINT AS item_id, ((r - 1 - i + 50) // 50)::INT AS option_id FROM (SELECT s_suppkey::BIGINT AS user_id, row_number() OVER (ORDER BY s_acctbal, s_suppkey) AS r FROM supplier), range(1, 51) AS t(i)"
_TEXT_CONSISTENT = f"SELECT user_id, item_id::VARCHAR AS item_id, option_id::VARCHAR AS option_id FROM ({_CONSISTENT})"


def _start(name: str = "s0", value: str | None = None) -> str:
    return f"{name} AS MATERIALIZED (SELECT user_id, {value or draw('user_id', '42')} AS s FROM r GROUP BY user_id)"


def _anchor(source: str, to: str) -> str:
    first = f"(SELECT arg_min(s, user_id) FROM {source})"
    return f"{to} AS MATERIALIZED (SELECT user_id, coalesce((s - {first}) / nullif((SELECT max(abs(s - {first})) FROM {source}), 0), 0) AS s FROM {source})"


def _averages(k: int, before: str) -> list[str]:
    return [f"w{k} AS MATERIALIZED (SELECT item_id, option_id, avg(s) AS w FROM r JOIN {before} USING (user_id) GROUP BY ALL)", f"t{k} AS MATERIALIZED (SELECT user_id, avg(w) AS s FROM r JOIN w{k} USING (item_id, option_id) GROUP BY user_id)"]


def _chain(responses: str, rounds: int, step, start: str | None = None, extra: list[str] = ()) -> str:
    ctes = [f"r AS MATERIALIZED ({responses})", *extra, _start(value=start)]
    for k in range(1, rounds + 1):
        ctes += step(k)
    return "WITH " + ", ".join(ctes)


def _anchored_step(k: int) -> list[str]:
    return [*_averages(k, f"s{k - 1}"), _anchor(f"t{k}", f"s{k}")]


def _ranked(last: str, digits: int = 6) -> str:
    return f" SELECT user_id, round(s, {digits}) + 0.0 AS score, row_number() OVER (ORDER BY round(s, {digits}) + 0.0 DESC, user_id) AS rank FROM {last}"


def diffprop(responses: str, rounds: int = ROUNDS) -> str:
    return _chain(responses, rounds, _anchored_step) + _ranked(f"s{rounds}")


def deflated(responses: str, rounds: int = ROUNDS) -> str:
    def step(k):
        mean = f"f{k} AS MATERIALIZED (SELECT user_id, s - (SELECT sum(l * s) / sum(l) FROM s{k - 1} JOIN n USING (user_id)) AS s FROM s{k - 1})"
        return [mean, *_averages(k, f"f{k}"), f"s{k} AS MATERIALIZED (SELECT user_id, s / (SELECT max(abs(s)) FROM t{k}) AS s FROM t{k})"]

    return _chain(responses, rounds, step, extra=["n AS MATERIALIZED (SELECT user_id, count(*) AS l FROM r GROUP BY user_id)"]) + _ranked(f"s{rounds}")


def _sums(k: int) -> list[str]:
    return [f"w{k} AS MATERIALIZED (SELECT item_id, option_id, sum(s) AS w FROM r JOIN s{k - 1} USING (user_id) GROUP BY ALL)", f"t{k} AS MATERIALIZED (SELECT user_id, sum(w) AS s FROM r JOIN w{k} USING (item_id, option_id) GROUP BY user_id)"]


def fiedler(responses: str, rounds: int) -> str:
    degree = "d AS MATERIALIZED (SELECT user_id, sum(n)::DOUBLE AS d FROM r JOIN (SELECT item_id, option_id, count(*) AS n FROM r GROUP BY ALL) USING (item_id, option_id) GROUP BY user_id)"

    def step(k):
        return [*_sums(k), f"m{k} AS MATERIALIZED (SELECT user_id, (2.0 * (SELECT max(d) FROM d) - d) * s{k - 1}.s + t{k}.s AS s FROM s{k - 1} JOIN d USING (user_id) JOIN t{k} USING (user_id))", _anchor(f"m{k}", f"s{k}")]

    return _chain(responses, rounds, step, extra=[degree]) + _ranked(f"s{rounds}")


def hits(responses: str, rounds: int = ROUNDS) -> str:
    return _chain(responses, rounds, lambda k: [*_sums(k), f"s{k} AS MATERIALIZED (SELECT user_id, s / (SELECT sqrt(sum(s * s)) FROM t{k}) AS s FROM t{k})"], "1.0") + _ranked(f"s{rounds}")


def truthfinder(responses: str, rounds: int = ROUNDS) -> str:
    def step(k):
        return [f"w{k} AS MATERIALIZED (SELECT item_id, option_id, 1 - exp(sum(ln(greatest(1 - s, 1e-12)))) AS w FROM r JOIN s{k - 1} USING (user_id) GROUP BY ALL)", f"s{k} AS MATERIALIZED (SELECT user_id, avg(w) AS s FROM r JOIN w{k} USING (item_id, option_id) GROUP BY user_id)"]

    return _chain(responses, rounds, step, "0.9") + _ranked(f"s{rounds}")


def investment(responses: str, rounds: int = 10, power: float = 1.2, pooled: bool = False) -> str:
    def step(k):
        value = f"i * pow(i, {power}) / sum(pow(i, {power})) OVER (PARTITION BY item_id)" if pooled else f"pow(i, {power})"
        return [
            f"e{k} AS MATERIALIZED (SELECT r.user_id, item_id, option_id, s / n AS e FROM r JOIN s{k - 1} ON r.user_id = s{k - 1}.user_id JOIN (SELECT user_id, count(*) AS n FROM r GROUP BY user_id) c ON r.user_id = c.user_id)",
            f"w{k} AS MATERIALIZED (SELECT item_id, option_id, i, {value} AS w FROM (SELECT item_id, option_id, sum(e) AS i FROM e{k} GROUP BY ALL))",
            f"t{k} AS MATERIALIZED (SELECT user_id, sum(w * e / i) AS s FROM e{k} JOIN w{k} USING (item_id, option_id) GROUP BY user_id)",
            f"s{k} AS MATERIALIZED (SELECT user_id, s / (SELECT max(s) FROM t{k}) AS s FROM t{k})",
        ]

    return _chain(responses, rounds, step, "1.0") + _ranked(f"s{rounds}")


def _with(name: str, rest: str) -> str:
    return f"WITH r AS MATERIALIZED ({R[name]}) {rest}"


_KEY = "key AS MATERIALIZED (SELECT item_id, option_id FROM (SELECT item_id, option_id, row_number() OVER (PARTITION BY item_id ORDER BY count(*) DESC, option_id) AS n FROM r GROUP BY item_id, option_id) WHERE n = 1)"
_AGREE = "agree AS MATERIALIZED (SELECT user_id, avg((r.option_id = key.option_id)::INT::DOUBLE) AS score FROM r JOIN key USING (item_id) GROUP BY user_id)"
_CORRECT = "correct AS MATERIALIZED (SELECT user_id, sum((r.option_id = key.option_id)::INT)::BIGINT AS score FROM r JOIN key USING (item_id) GROUP BY user_id)"
_PART = "part AS MATERIALIZED (SELECT user_id, count(*) AS score FROM r GROUP BY user_id)"


def _average_rank(name: str) -> str:
    return f"(SELECT user_id, rank() OVER (ORDER BY score) + (count(*) OVER (PARTITION BY score) - 1) / 2.0 AS x FROM (SELECT user_id, round(score, 9) AS score FROM {name}))"


def _stats(order_by_rank: str) -> str:
    return f"SELECT user_id, row_number() OVER (ORDER BY {order_by_rank}) AS rank"


_DECILE = (
    f"WITH c AS (SELECT * FROM ({diffprop(R['R1'])})), r AS MATERIALIZED ({R['R1']}), m AS (SELECT count(*) AS m, greatest(1, ceil(count(*) * 0.1)) AS size FROM c), "
    "side AS (SELECT user_id, 'low' AS side FROM c, m WHERE rank <= size UNION ALL SELECT user_id, 'high' FROM c, m WHERE rank > m - size), "
    "n AS (SELECT side, item_id, option_id, count(*) AS n FROM r JOIN side USING (user_id) GROUP BY ALL), p AS (SELECT side, item_id, n / sum(n) OVER (PARTITION BY side, item_id) AS p FROM n), "
    "h AS (SELECT side, item_id, sum(-p * ln(p)) AS h FROM p GROUP BY ALL) SELECT side, round(avg(h), 6) AS entropy, count(*) AS n_items FROM h GROUP BY side"
)


def oracle_sql() -> dict[str, str]:
    out = {
        "resp_supplier_brand": R["R1"], "resp_supplier_part": R["R2"], "resp_customer_quarter": R["R3"], "resp_user_day": R["R4"], "resp_vector_dim": R["R5"], "resp_doc_features": R["R6"], "resp_conv_turn": R["R7"],
        "resp_consistent": _CONSISTENT, "resp_graded": _GRADED, "resp_nominal": _nominal(""), "resp_nominal_guess": _nominal("guess"),
        "resp_binary3p": f"SELECT user_id, item_id, (u < 0.25 + 0.75 * (1.0 / (1.0 + exp(-(a * (theta - b[1]))))))::INT AS option_id FROM ({_PAIRS})",
        "resp_step": f"SELECT user_id, item_id, ((theta >= t[1])::INT + (theta >= t[2])::INT)::INT AS option_id FROM ({_PAIRS})",
        "resp_thinned": f"SELECT g.user_id, g.item_id, g.option_id FROM ({_GRADED}) g WHERE {draw('user_id', 'item_id', repr('keep'), '42')} < 0.6",
        "passage_items": "SELECT doc_id::BIGINT AS user_id, item_id::BIGINT AS item_id FROM documents d JOIN benchmark b ON length(b.text) > 0 AND contains(d.text, b.text)",
        "page_features": "SELECT page_id::BIGINT AS user_id, tag AS item_id, least(3, len(regexp_extract_all(coalesce(html, ''), '<' || tag || '[ >]')))::VARCHAR AS option_id FROM pages, (SELECT unnest(['p', 'a', 'div', 'li', 'script']) AS tag)",
        "response_stats": _with("R1", "SELECT n_users, n_items, n_options, n_answers, max_options, round(n_answers / (n_users * n_items), 6) AS density FROM (SELECT count(DISTINCT user_id) AS n_users, count(DISTINCT item_id) AS n_items, count(*) AS n_answers FROM r), (SELECT sum(k)::BIGINT AS n_options, max(k) AS max_options FROM (SELECT count(DISTINCT option_id) AS k FROM r GROUP BY item_id))"),
        "item_option_counts": _with("R1", "SELECT item_id, option_id, count(*) AS n FROM r GROUP BY ALL"),
        "user_degrees": _with("R2", "SELECT user_id, count(*) AS degree FROM r GROUP BY user_id"),
        "option_entropy": _with("R1", "SELECT item_id, round(sum(-p * ln(p)), 6) AS entropy FROM (SELECT item_id, count(*) / sum(count(*)) OVER (PARTITION BY item_id) AS p FROM r GROUP BY item_id, option_id) GROUP BY item_id"),
        "one_hot_edges": _with("R1", "SELECT user_id, ix - 1 AS option_ix, 1 AS value FROM r JOIN (SELECT item_id, option_id, row_number() OVER (ORDER BY item_id, option_id) AS ix FROM (SELECT DISTINCT item_id, option_id FROM r)) USING (item_id, option_id)"),
        "wide_matrix": _with("R1", "SELECT user_id, " + ", ".join(f"max(option_id) FILTER (item_id = 'Brand#{i}{j}') AS b{i}{j}" for i in range(1, 6) for j in range(1, 6)) + " FROM r GROUP BY user_id"),
        "packed_rows": _with("R1", "SELECT user_id, string_agg(item_id || '=' || option_id, ',' ORDER BY item_id) AS choices FROM r GROUP BY user_id"),
        "filtered_answers": _with("R4", "SELECT count(*) AS n_answers, count(DISTINCT user_id) AS n_users FROM r WHERE user_id IN (SELECT user_id FROM r GROUP BY user_id HAVING count(*) >= 2)"),
        "avg_step": _chain(R["R1"], 1, lambda k: _averages(k, "s0")) + " SELECT user_id, round(s, 6) AS score FROM t1",
        "avghits_rounds": _chain(R["R1"], 5, lambda k: [*_averages(k, f"s{k - 1}"), f"s{k} AS MATERIALIZED (SELECT * FROM t{k})"]) + " SELECT user_id, round(s, 6) AS score FROM s5",
        "update_matrix": _with("R1", ", a AS (SELECT user_id, item_id, option_id, count(*) OVER (PARTITION BY user_id) AS nu, count(*) OVER (PARTITION BY item_id, option_id) AS no FROM r) SELECT a.user_id AS u, r.user_id AS v, round(sum(1.0 / (nu * no)), 6) AS value FROM a JOIN r USING (item_id, option_id) GROUP BY ALL"),
        "diff_update_matrix": _with("R1", ", p AS (SELECT user_id, row_number() OVER (ORDER BY user_id) AS pos FROM (SELECT DISTINCT user_id FROM r)), a AS (SELECT user_id, item_id, option_id, count(*) OVER (PARTITION BY user_id) AS nu, count(*) OVER (PARTITION BY item_id, option_id) AS no FROM r), u AS (SELECT x.pos AS i, y.pos AS j, sum(1.0 / (nu * no)) AS v FROM a JOIN r USING (item_id, option_id) JOIN p x ON x.user_id = a.user_id JOIN p y ON y.user_id = r.user_id GROUP BY ALL), g AS (SELECT x.pos AS i, y.pos AS j, coalesce(v, 0) AS v FROM p x CROSS JOIN p y LEFT JOIN u ON u.i = x.pos AND u.j = y.pos), c AS (SELECT i, j - 1 AS j, sum(v) OVER (PARTITION BY i ORDER BY j DESC) AS s FROM g) SELECT x.i, x.j, round(y.s - x.s, 6) + 0.0 AS value FROM c x JOIN c y ON y.i = x.i + 1 AND y.j = x.j WHERE x.j > 0"),
        "diffprop_supplier_brand": diffprop(R["R1"]), "diffprop_customer_quarter": diffprop(R["R3"]), "diffprop_user_day": diffprop(R["R4"]), "diffprop_consistent": diffprop(_TEXT_CONSISTENT),
        "diffprop_gram": diffprop(R["R1"]), "diffprop_arrow": diffprop(R["R2"], 4), "diffprop_joins": diffprop(R["R2"], 4), "diffprop_diff_step": diffprop(R["R1"], 3), "diffprop_deflated": deflated(R["R1"], 10),
        "diffprop_direct": _truth_order(), "fiedler_direct": _truth_order(), "diffprop_naive": _truth_order(),
        "laplacian_edges": _with("R1", ", c AS (SELECT a.user_id AS u, b.user_id AS v, count(*) AS n FROM r a JOIN r b USING (item_id, option_id) WHERE a.user_id <> b.user_id GROUP BY ALL) SELECT u, v, -n AS value FROM c UNION ALL SELECT u, u, sum(n)::BIGINT FROM c GROUP BY u"),
        "fiedler_rounds": fiedler(R["R1"], 10),
        "p_matrix_violations": _with("R1", ", s AS (SELECT item_id, option_id, max(rank) - min(rank) + 1 AS span, count(*) AS choosers FROM r JOIN (SELECT user_id, row_number() OVER (ORDER BY user_id) AS rank FROM (SELECT DISTINCT user_id FROM r)) USING (user_id) GROUP BY ALL) SELECT * FROM s WHERE span <> choosers"),
        "consistency_check": "SELECT 'consistent' AS dataset, true AS consistent UNION ALL SELECT 'supplier_brand', false",
        "duplicate_users": _with("R4", "SELECT min(user_id) AS kept, count(*) AS multiplicity FROM (SELECT user_id, string_agg(item_id || '=' || option_id, ',' ORDER BY item_id) AS c FROM r GROUP BY user_id) GROUP BY c"),
        "components": _components(),
        "hits_rounds": hits(R["R2"]), "truthfinder_rounds": truthfinder(R["R2"], 5), "investment_rounds": investment(R["R2"]), "pooled_rounds": investment(R["R2"], power=1.4, pooled=True),
        "participation": _with("R2", "SELECT user_id, count(*) AS score FROM r GROUP BY user_id"),
        "majority_key": _with("R2", f", {_KEY} SELECT * FROM key"),
        "true_answer": _with("R2", f", {_KEY}, {_CORRECT} SELECT * FROM correct"),
        "majority_agreement": _with("R2", f", {_KEY}, {_AGREE} SELECT user_id, round(score, 6) AS score FROM agree"),
        "threshold_select": _with("R2", f", {_KEY}, {_CORRECT}, {_PART} SELECT user_id, part.score AS answers, correct.score AS correct FROM correct JOIN part USING (user_id) WHERE part.score >= 10 AND correct.score * (SELECT sum(score) FROM part) >= part.score * (SELECT sum(score) FROM correct)"),
        "decile_entropy": _DECILE,
        "oriented_ranking": f"WITH c AS MATERIALIZED (SELECT user_id, score FROM ({diffprop(R['R1'])})), h AS MATERIALIZED ({_DECILE}), o AS (SELECT user_id, CASE WHEN (SELECT entropy FROM h WHERE side = 'low') < (SELECT entropy FROM h WHERE side = 'high') THEN score ELSE -score END + 0.0 AS score FROM c) SELECT user_id, score, row_number() OVER (ORDER BY score DESC, user_id) AS rank FROM o",
        "infer_truth": f"WITH r AS MATERIALIZED ({R['R1']}), c AS MATERIALIZED ({diffprop(R['R1'])}) SELECT item_id, option_id, round(m, 6) AS mean_rank FROM (SELECT item_id, option_id, avg(rank::DOUBLE) AS m, row_number() OVER (PARTITION BY item_id ORDER BY avg(rank::DOUBLE), option_id) AS n FROM r JOIN c USING (user_id) GROUP BY item_id, option_id) WHERE n = 1",
        "option_weights": f"WITH r AS MATERIALIZED ({R['R1']}), c AS MATERIALIZED ({diffprop(R['R1'])}) SELECT item_id, option_id, ((s * 2 + n * 10 - ((s * 2 + n * 10) % (n * 20) + n * 20) % (n * 20)) // (n * 20)) / 100000.0 AS weight FROM (SELECT item_id, option_id, sum(round(score * 1000000)::BIGINT)::BIGINT AS s, count(*) AS n FROM r JOIN c USING (user_id) GROUP BY ALL)",
        "spearman": _with("R2", f", {_KEY}, {_AGREE}, {_PART} SELECT round(corr(a.x, b.x), 6) AS rho FROM {_average_rank('agree')} a JOIN {_average_rank('part')} b USING (user_id)"),
        "kendall": _with("R2", f", {_KEY}, {_AGREE}, {_PART}, b AS (SELECT user_id, agree.score AS x, part.score AS y FROM agree JOIN part USING (user_id)), p AS (SELECT sign(a.x - b.x) * sign(a.y - b.y) AS s, a.x <> b.x AS nx, a.y <> b.y AS ny FROM b a JOIN b ON a.user_id < b.user_id) SELECT sum((s > 0)::INT)::BIGINT AS concordant, sum((s < 0)::INT)::BIGINT AS discordant, round((sum((s > 0)::INT) - sum((s < 0)::INT)) / sqrt(sum(nx::INT)::DOUBLE * sum(ny::INT)), 6) AS tau FROM p"),
        "displacement": _with("R2", f", {_KEY}, {_AGREE}, {_CORRECT} SELECT round(avg(abs(a.k - b.k)) / count(*), 6) AS displacement FROM (SELECT user_id, row_number() OVER (ORDER BY round(score, 9) DESC, user_id) AS k FROM agree) a JOIN (SELECT user_id, row_number() OVER (ORDER BY score DESC, user_id) AS k FROM correct) b USING (user_id)"),
        "eigvec_variance": "WITH d AS (SELECT lead(s_acctbal) OVER (ORDER BY s_suppkey) - s_acctbal AS d FROM supplier) SELECT round(var_pop(d / (SELECT sqrt(sum(d * d)) FROM d)), 6) AS variance FROM d WHERE d IS NOT NULL",
        "auc_quality": "WITH l AS (SELECT doc_id AS user_id, n_chars::DOUBLE AS score, quality AS label FROM documents JOIN labels USING (doc_id)), k AS (SELECT label, rank() OVER (ORDER BY score) + (count(*) OVER (PARTITION BY score) - 1) / 2.0 AS x FROM l) SELECT round((sum(x) FILTER (label = 1) - sum((label = 1)::INT) * (sum((label = 1)::INT) + 1) / 2.0) / (sum((label = 1)::INT) * sum((label = 0)::INT)), 6) AS auc FROM k",
        "mean_correctness": _with("R1", f", {_KEY} SELECT round(avg((r.option_id = key.option_id)::INT::DOUBLE), 6) AS correctness FROM r JOIN key USING (item_id)"),
        "accuracy_by_region": _with("R1", f", {_KEY}, {_AGREE} SELECT r_name AS region, n_name AS nation, count(*) AS n_users, round(avg(score), 6) AS agreement FROM agree JOIN supplier ON s_suppkey = user_id JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)"),
        "topk_users": _with("R2", f", {_KEY}, {_CORRECT} SELECT user_id, score FROM correct ORDER BY score DESC, user_id LIMIT 10"),
        "topk_per_region": _with("R2", f", {_KEY}, {_CORRECT} SELECT region, user_id, score, k AS rank FROM (SELECT r_name AS region, user_id, score, row_number() OVER (PARTITION BY r_name ORDER BY score DESC, user_id) AS k FROM correct JOIN supplier ON s_suppkey = user_id JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey) WHERE k <= 3"),
        "setops_top_decile": _with("R2", f", {_KEY}, {_CORRECT}, {_AGREE}, a AS (SELECT user_id FROM correct ORDER BY score DESC, user_id LIMIT 20), b AS (SELECT user_id FROM (SELECT user_id, round(score, 9) AS score FROM agree) ORDER BY score DESC, user_id LIMIT 20) SELECT 'both' AS part, user_id FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'first', user_id FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT 'second', user_id FROM (SELECT * FROM b EXCEPT SELECT * FROM a)"),
        "asof_answer": "SELECT event_id, user_id, prev AS last_view FROM (SELECT event_id, user_id, event_type, max(CASE WHEN event_type = 'view' THEN epoch_us(ts) END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prev FROM events) WHERE event_type = 'purchase'",
        "interval_answers": "SELECT a.user_id, count(*) AS n_pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR GROUP BY a.user_id",
        "json_props_item": "SELECT event_type, (json_extract(props, '$.k')::INT % 10)::INT AS bucket, count(*) AS n FROM events GROUP BY ALL",
        "semi_anti_users": "SELECT 'with_orders' AS part, count(*) AS n FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders) UNION ALL SELECT 'without_orders', count(*) FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)",
        "stream_final_answers": R["R4"],
        "stream_sliding": "SELECT (d - INTERVAL (k) DAY)::DATE::VARCHAR AS window_start, event_type, count(*) AS n FROM (SELECT ts::DATE AS d, event_type FROM events), range(0, 7) AS t(k) GROUP BY ALL",
        "stream_sessions": "WITH e AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS n FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(n) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM e) SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n_events FROM s GROUP BY user_id, k",
        "cost_model": _with("R1", ", c AS MATERIALIZED (SELECT count(DISTINCT user_id)::DOUBLE AS m, count(DISTINCT item_id)::DOUBLE AS n FROM r) SELECT 'diffprop_power' AS method, m * n * 20 AS steps FROM c UNION ALL SELECT 'fiedler_direct', m * m * n FROM c"),
    }
    return out


def _truth_order() -> str:
    """On consistent data the order found is the true one, told from its first user on."""
    return "WITH r AS (SELECT s_suppkey::BIGINT AS user_id, row_number() OVER (ORDER BY s_acctbal, s_suppkey) AS r, count(*) OVER () AS m FROM supplier), f AS (SELECT arg_min(r, user_id) AS a, max(m) AS m FROM r) SELECT user_id, CASE WHEN a * 2 <= f.m THEN r ELSE f.m + 1 - r END AS rank FROM r, f"


def _components() -> str:
    return f"""WITH RECURSIVE r AS MATERIALIZED ({R['R7']}), e AS MATERIALIZED (SELECT DISTINCT a.user_id AS x, min(b.user_id) OVER (PARTITION BY a.user_id) AS y FROM r a JOIN r b USING (item_id, option_id)),
    o AS MATERIALIZED (SELECT item_id, option_id, user_id FROM r),
    walk(root, user_id) AS (SELECT user_id, user_id FROM (SELECT DISTINCT user_id FROM r) UNION SELECT w.root, b.user_id FROM walk w JOIN o a ON a.user_id = w.user_id JOIN o b ON b.item_id = a.item_id AND b.option_id = a.option_id)
    SELECT user_id, min(root) AS component FROM walk GROUP BY user_id"""
