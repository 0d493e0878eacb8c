"""SQL surface: a table function that ranks many small data sets at once, and the md5 draw.

    SELECT * FROM ability_rank(TABLE(answers) PARTITION BY (dataset), 'diffprop')

Methods are those of ``operators.dense``; the spectral ones come oriented by entropy.

Each partition is one data set, solved in one Python worker; large ones go through the DataFrame API.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Row, SparkSession
from pyspark.sql import functions as F

from ..operators import dense

METHODS = (*dense.UNPRIVILEGED, "majority_agreement")


class AbilityRank:
    """Rows user_id, item_id, option_id of one partition in; user_id, score, rank out."""

    def __init__(self):
        self.rows, self.method = [], "diffprop"

    def eval(self, row: Row, method: str = "diffprop"):
        self.method = method
        if row["user_id"] is not None and row["item_id"] is not None and row["option_id"] is not None:
            self.rows.append((row["user_id"], row["item_id"], row["option_id"]))
        if len(self.rows) > dense.MOST_ANSWERS:
            raise ValueError("too many answers for one data set: use the DataFrame API")

    def terminate(self):
        if not self.rows:
            return
        a = dense.Answers.of(*(np.array(x) for x in zip(*self.rows)))
        s = np.asarray(dense.scores(a, self.method), float)
        rank = dense.descending(a, s)
        for i in np.argsort(rank).tolist():
            yield int(a.users[i]), float(s[i]), int(rank[i])


def register_sql(spark: SparkSession) -> None:
    """Makes ability_rank (a table function) and uniform_draw (of a key) known to SQL."""
    spark.udtf.register("ability_rank", F.udtf(AbilityRank, returnType="user_id bigint, score double, rank bigint"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION uniform_draw(key STRING) RETURNS DOUBLE RETURN CAST(conv(substring(md5(key), 1, 13), 16, 10) AS BIGINT) / 4503599627370496.0D")


def rank_each(df, dataset: str, method: str = "diffprop"):
    """The same by applyInPandas: dataset, user_id, score for every data set of a table."""

    def solve(key, pdf: pd.DataFrame) -> pd.DataFrame:
        a = dense.Answers.of(pdf["user_id"].to_numpy(), pdf["item_id"].to_numpy(), pdf["option_id"].to_numpy())
        return pd.DataFrame({dataset: key[0], "user_id": a.users, "score": np.asarray(dense.scores(a, method), float)})

    kind = df.schema[dataset].dataType.simpleString()
    return df.groupBy(dataset).applyInPandas(solve, f"`{dataset}` {kind}, user_id long, score double")
