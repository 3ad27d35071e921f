"""Hand examples of the four cases, and the functions under them."""

import pytest
from pyspark.sql import functions as F

from deltamp.functions.vectors import register, select_by_key
from deltamp.operators.classify import apply_incremental, classify

ROWS = "id string, old array<double>, del_vec array<double>, add_vec array<double>"
HAND = [
    ("T0", [2, 5, 3], None, [3, 4, 9], "no_deletion", [2, 4, 3]), ("T1", [2, 5, 3], [4, 6, 7], None, "deletion_no_effect", [2, 5, 3]),
    ("T2", [2, 5, 3], [2, 9, 9], [2, 8, 1], "covered_reset", [2, 5, 1]), ("T3", [1, 1, 4, 4], [1, 1, 9, 9], [0, 3, 9, 9], "exposed_reset", None),
    ("T4", [2, 5, 3], [2, 5, 3], None, "exposed_reset", None), ("T9", None, None, [1, 2, 3], "no_deletion", [1, 2, 3]),
]


@pytest.mark.parametrize("how", ["min", "max"])
def test_hand_vectors(spark, how):
    sign = 1.0 if how == "min" else -1.0
    flip = lambda v: None if v is None else [sign * x for x in v]
    rows = spark.createDataFrame([(i, flip(o), flip(d), flip(a)) for i, o, d, a, _, _ in HAND], ROWS)
    got = {r.id: r for r in apply_incremental(classify(rows, how), how).collect()}
    for i, _, _, _, case, new in HAND:
        assert got[i].condition == case
        if new is not None:
            assert got[i].new == flip(new)


@pytest.mark.parametrize("width", [3, 32, 70])
def test_blocks_agree_with_plain_aggregates(spark, width):
    rows = spark.range(60).select((F.col("id") % 4).alias("k"), F.transform(F.sequence(F.lit(1), F.lit(width)), lambda i: ((i * F.col("id") * 37) % 101).cast("double")).alias("vec"))
    out = {r.k: r for r in select_by_key(rows, ["k"], width, {"lo": ("min", None), "odd": ("max", "k % 2 = 1")}).collect()}
    for k in range(4):
        vecs = [[float((i * n * 37) % 101) for i in range(1, width + 1)] for n in range(60) if n % 4 == k]
        assert out[k].lo == [min(c) for c in zip(*vecs)]
        assert out[k].odd == ([max(c) for c in zip(*vecs)] if k % 2 else None)


def test_sql_functions(spark):
    register(spark)
    r = spark.sql("SELECT vec_min(array(1D, 5D), array(2D, 3D)) a, vec_max(array(1D, 5D), array(2D, 3D)) b, vec_dot(array(1D, 2D), array(3D, 4D)) c, vec_relu(array(-1D, 2D)) d, vec_argdiff(array(1D, 2D), array(1D, 3D)) e").first()
    assert (r.a, r.b, r.c, r.d, r.e) == ([1.0, 3.0], [2.0, 5.0], 11.0, [0.0, 2.0], [1])
    assert [(x.dim, x.val) for x in spark.sql("SELECT * FROM vec_unnest(array(7D, 8D))").collect()] == [(0, 7.0), (1, 8.0)]
