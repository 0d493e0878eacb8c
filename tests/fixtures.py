"""A hand-made data set whose only consecutive order is 1-2-3-4 (or its reverse)."""

SCHEMA = "user_id long, item_id string, option_id string"
ROWS = [(1, "t1", "A"), (1, "t2", "A"), (1, "t3", "A"), (2, "t1", "A"), (2, "t2", "B"), (2, "t3", "A"), (3, "t1", "B"), (3, "t2", "B"), (3, "t3", "A"), (4, "t1", "B"), (4, "t2", "C"), (4, "t3", "B")]
CYCLE = [(1, "a", "x"), (2, "a", "x"), (3, "a", "y"), (1, "b", "y"), (2, "b", "x"), (3, "b", "x"), (1, "c", "x"), (2, "c", "y"), (3, "c", "x")]


def path_data(spark):
    return spark.createDataFrame(ROWS, SCHEMA)


def order_of(scores):
    found = [r["user_id"] for r in scores.orderBy("score", "user_id").collect()]
    return found if found[0] < found[-1] else found[::-1]
