"""Quality rules: a threshold table compiled into one Spark projection, without user functions.

Measures and rules are plain column expressions.  Arrays that an expression needs more than once
are bound with ``let`` so that they are computed once a row.

Null and empty texts have no words: every count is 0 and ``base_failed`` is true.  Rows that repeat
are judged apart; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Frequent words of the four languages of the corpus.
STOP_WORDS = (
    "the of and to in a is that for it as with was on be by at this are or an not from but have "
    "der die das und ist in den von zu mit sich des auf nicht ein eine dem es im "
    "le la les de et un une des du que qui dans en pour par est sur au pas "
    "el los las y en un una que se del por con para su al lo es"
).split()

#: (rule, measure, least, most); a null bound is open.  Measures are columns of ``measures``.
RULES = (
    ("mean_word_length", "mean_word_length", 1.5, 20.0),
    ("symbol_ratio", "symbol_ratio", None, 0.35),
    ("shout_ratio", "shout_ratio", None, 0.5),
    ("lone_mark_ratio", "lone_mark_ratio", None, 0.3),
    ("stop_words_of_long_texts", "stop_ratio_long", 0.01, None),
    ("repeated_line_ratio", "dup_line_ratio", None, 0.5),
    ("cut_line_ratio", "ellipsis_line_ratio", None, 0.5),
)

BREAKS = r"[\x20\x09-\x0D]+"


def let(value: Column, body) -> Column:
    """body(x) with x computed once: a lambda variable over a one-element array."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words(text: Column) -> Column:
    trimmed = F.regexp_replace(text, r"^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$", "")
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, BREAKS))


def repeated_words(w: Column, width: int = 5) -> Column:
    """Words in windows of ``width`` words whose sequence is found twice or more in the text."""

    def of(h: Column) -> Column:
        def marked(s: Column) -> Column:
            same = lambda j, k: (k >= 1) & (k <= F.size(s)) & (F.get(s, k - 1)["h"] == F.get(s, j)["h"])
            hit = F.filter(s, lambda x, j: same(j, j) | same(j, j + 2))
            at = F.array_sort(F.transform(hit, lambda x: x["i"]))
            return let(at, lambda p: F.aggregate(F.zip_with(p, F.slice(p, 2, F.size(p)), lambda a, b: F.when(b.isNull(), width).otherwise(F.least(F.lit(width), b - a))), F.lit(0).cast("long"), lambda acc, x: acc + x))

        return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0).cast("long")).otherwise(let(F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i")))), marked))

    hashes = F.transform(F.sequence(F.lit(0), F.size(w) - width), lambda i: F.xxhash64(*[F.get(w, i + k) for k in range(width)]))
    return F.when(F.size(w) < width, F.lit(0).cast("long")).otherwise(let(hashes, of))


def measures(df: DataFrame, text: str = "text") -> DataFrame:
    """Adds the counts and ratios of each text; the word array itself is not kept."""
    t = F.coalesce(F.col(text), F.lit(""))
    of_words = let(
        words(t),
        lambda w: F.struct(
            F.size(w).cast("long").alias("n_words"),
            repeated_words(w).alias("n_repeat_words"),
        ),
    )
    # words that are a stop word with at most one mark behind it
    stop_pattern = r"(?i)(?<![^\x20\x09-\x0D])(?:" + "|".join(sorted(set(STOP_WORDS))) + r")[.,;:!?]?(?![^\x20\x09-\x0D])"
    lines = F.filter(F.split(t, "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    of_lines = let(lines, lambda x: F.struct(F.size(x).cast("long").alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"), F.size(F.filter(x, lambda y: y.endswith("...") | y.endswith("…"))).cast("long").alias("n_cut_lines")))
    out = df.select(
        "*",
        of_words.alias("_w"),
        of_lines.alias("_l"),
        F.length(F.regexp_replace(t, BREAKS, "")).cast("long").alias("word_chars"),
        F.length(F.regexp_replace(t, r"[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
        F.regexp_count(t, F.lit(r"!!")).cast("long").alias("n_shouts"),
        F.regexp_count(t, F.lit(r"(?<![^\x20\x09-\x0D])[^\p{L}\p{N}\x20\x09-\x0D](?![^\x20\x09-\x0D])")).cast("long").alias("n_lone_marks"),
        F.regexp_count(t, F.lit(stop_pattern)).cast("long").alias("n_stops"),
    )
    per = lambda a, b: F.when(b == 0, F.lit(0.0)).otherwise(a / b)
    n, k = F.col("_w.n_words"), F.col("_l.n_lines")
    return out.select(
        *[F.col(c) for c in df.columns], n.alias("n_words"), "word_chars", "n_symbols", F.col("_l.n_dup_lines").alias("n_dup_lines"), F.col("_w.n_repeat_words").alias("n_repeat_words"),
        per(F.col("word_chars"), n).alias("mean_word_length"), per(F.col("n_symbols"), n).alias("symbol_ratio"), per(F.col("n_shouts"), n).alias("shout_ratio"), per(F.col("n_lone_marks"), n).alias("lone_mark_ratio"),
        F.when(n < 100, F.lit(1.0)).otherwise(per(F.col("n_stops"), n)).alias("stop_ratio_long"), per(F.col("_l.n_dup_lines"), k).alias("dup_line_ratio"), per(F.col("_l.n_cut_lines"), k).alias("ellipsis_line_ratio"),
    )


def verdict(rules=RULES) -> Column:
    """The rule table as one condition: every measure within its bounds."""
    ok = F.lit(True)
    for _, measure, least, most in rules:
        if least is not None:
            ok = ok & (F.col(measure) >= least)
        if most is not None:
            ok = ok & (F.col(measure) <= most)
    return ok


def broken(rules=RULES) -> Column:
    """Names of the rules that a row breaks, comma-joined in table order."""
    bad = []
    for name, measure, least, most in rules:
        wrong = F.lit(False)
        if least is not None:
            wrong = wrong | (F.col(measure) < least)
        if most is not None:
            wrong = wrong | (F.col(measure) > most)
        bad.append(F.when(wrong, F.lit(name)))
    return F.concat_ws(",", *bad)


def apply_rules(df: DataFrame, text: str = "text", rules=RULES) -> DataFrame:
    """df with its measures, ``base_failed``, ``kept`` and the names of broken rules.

    Columns of df that clash with a measure's name are replaced.
    """
    made = {"n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "mean_word_length", "symbol_ratio", "shout_ratio", "lone_mark_ratio", "stop_ratio_long", "dup_line_ratio", "ellipsis_line_ratio", "_w", "_l", "n_shouts", "n_lone_marks", "n_stops", "base_failed", "kept", "broken_rules"} - {text}
    m = measures(df.drop(*[c for c in df.columns if c.lower() in made]), text)
    base = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    return m.select("*", base.alias("base_failed"), (~base & verdict(rules)).alias("kept"), broken(rules).alias("broken_rules"))


def quality_rules_report(df: DataFrame) -> DataFrame:
    """doc_id with the counts and the verdict."""
    return apply_rules(df.select("doc_id", "text")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "broken_rules")


def oracle() -> str:
    """``quality_rules_report`` over ``documents`` in DuckDB SQL."""
    stops = "|".join(sorted(set(STOP_WORDS)))
    tests = {}
    for name, measure, least, most in RULES:
        tests[name] = " OR ".join(f"{measure} {op} {bound}" for op, bound in (("<", least), (">", most)) if bound is not None)
    names = ", ".join(f"CASE WHEN {t} THEN '{n}' END" for n, t in tests.items())
    per = lambda a, b: f"CASE WHEN {b} = 0 THEN 0.0 ELSE {a} / {b} END"
    return f"""
WITH d AS MATERIALIZED (SELECT row_number() OVER () AS k, doc_id, coalesce(text, '') AS t FROM documents),
w AS MATERIALIZED (SELECT k, doc_id, t, regexp_extract_all(t, '[^\\x20\\x09-\\x0D]+') AS ws, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS ls FROM d),
g AS (SELECT k, i, count(*) OVER (PARTITION BY k, g) AS n FROM (SELECT k, i, ws[i:i + 4] AS g FROM (SELECT k, ws, unnest(range(1, len(ws) - 3)) AS i FROM w WHERE len(ws) >= 5))),
c AS (SELECT k, sum(s)::BIGINT AS n_repeat_words FROM (SELECT k, least(5, coalesce(lead(i) OVER (PARTITION BY k ORDER BY i) - i, 5)) AS s FROM g WHERE n > 1) GROUP BY k),
m AS (SELECT w.k, doc_id, len(ws)::BIGINT AS n_words, length(array_to_string(ws, ''))::BIGINT AS word_chars, length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
  (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words, len(ls) AS n_lines,
  len(list_filter(ls, lambda x: suffix(x, '...') OR suffix(x, '…'))) AS n_cut, len(regexp_extract_all(t, '!!')) AS n_shouts,
  len(list_filter(ws, lambda x: length(x) = 1 AND NOT regexp_matches(x, '[\\p{{L}}\\p{{N}}]'))) AS n_lone, len(list_filter(ws, lambda x: regexp_full_match(lower(x), '({stops})[.,;:!?]?'))) AS n_stops
  FROM w LEFT JOIN c USING (k)),
r AS (SELECT *, {per('word_chars', 'n_words')} AS mean_word_length, {per('n_symbols', 'n_words')} AS symbol_ratio, {per('n_shouts', 'n_words')} AS shout_ratio, {per('n_lone', 'n_words')} AS lone_mark_ratio,
  CASE WHEN n_words < 100 THEN 1.0 ELSE n_stops / n_words END AS stop_ratio_long, {per('n_dup_lines', 'n_lines')} AS dup_line_ratio, {per('n_cut', 'n_lines')} AS ellipsis_line_ratio FROM m),
v AS (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed, concat_ws(',', {names}) AS broken_rules FROM r)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND broken_rules = '' AS kept, broken_rules FROM v""".replace("\\\\", "\\")
