import numpy as np
import pytest

from relmix.functions import vectors as V
from relmix.operators import algebra as A
from relmix.operators import layouts as L
from relmix.operators.merge import MergeError, append_merge, distinct_merge, overwrite_merge


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.fixture(scope="module")
def small(spark):
    return spark.createDataFrame([(1, 1.0, 2.0), (2, 3.0, 4.0)], "tid int, d1 double, d2 double")


def test_layouts_of_the_two_by_two_example(spark, small):
    cells = L.convert(small, "wide", "coordinate", 2)
    assert rows(cells) == [(1, 1, 1.0), (1, 2, 2.0), (2, 1, 3.0), (2, 2, 4.0)]
    assert rows(L.convert(small, "wide", "vector", 2)) == [(1, [1.0, 2.0]), (2, [3.0, 4.0])]


@pytest.mark.parametrize("a", ["wide", "vector", "coordinate"])
@pytest.mark.parametrize("b", ["wide", "vector", "coordinate"])
def test_every_round_trip(small, a, b):
    start = L.convert(small, "wide", a, 2)
    assert rows(L.convert(L.convert(start, a, b, 2), b, "wide", 2)) == rows(small)


def test_means_agree_between_layouts(spark, small):
    r = spark.createDataFrame([(1, 1, 0.25), (2, 1, 0.75), (1, 2, 0.75), (2, 2, 0.25)], "tid int, comp int, p double")
    wide = {x[0]: list(x[1:]) for x in rows(L.mean_wide(r, small, 2))}
    assert wide == {1: [2.5, 3.5], 2: [1.5, 2.5]}
    assert {x.comp: x["mean"] for x in L.mean_vector(r, L.wide_to_vector(small, 2), 2).collect()} == wide
    long = {(x.comp, x.c): x["mean"] for x in L.mean_coordinate(r, L.convert(small, "wide", "coordinate", 2)).collect()}
    assert long == {(k, i + 1): m for k, ms in wide.items() for i, m in enumerate(ms)}


def cells(spark, m):
    return spark.createDataFrame([(i, j, float(m[i, j])) for i in range(m.shape[0]) for j in range(m.shape[1])], "r int, c int, v double")


@pytest.mark.parametrize(("name", "plus", "times"), [("sum_times", np.sum, np.multiply), ("min_plus", np.min, np.add), ("max_plus", np.max, np.add), ("max_times", np.max, np.multiply), ("max_min", np.max, np.minimum)])
def test_semiring_products_against_numpy(spark, name, plus, times):
    rng = np.random.default_rng(3)
    a, b = rng.integers(1, 9, (3, 4)).astype(float), rng.integers(1, 9, (4, 2)).astype(float)
    want = [(i, j, plus([times(a[i, k], b[k, j]) for k in range(4)])) for i in range(3) for j in range(2)]
    ring = A.SEMIRINGS[name]
    assert rows(A.mm_join(cells(spark, a), cells(spark, b), ring)) == want
    v = spark.createDataFrame([(k, float(b[k, 0])) for k in range(4)], "i int, v double")
    assert rows(A.mv_join(cells(spark, a), v, ring, small=True)) == [(i, x) for i, j, x in want if j == 0]


def test_hadamard_addition_and_transpose(spark):
    a, b = np.array([[1.0, 2.0], [3.0, 4.0]]), np.array([[5.0, 6.0], [7.0, 8.0]])
    assert rows(A.hadamard_rowsum(cells(spark, a), cells(spark, b))) == [(0, 17.0), (1, 53.0)]
    assert rows(A.matrix_add(cells(spark, a), cells(spark, b))) == [(0, 0, 6.0), (0, 1, 8.0), (1, 0, 10.0), (1, 1, 12.0)]
    assert rows(A.transpose(cells(spark, a))) == [(0, 0, 1.0), (0, 1, 3.0), (1, 0, 2.0), (1, 1, 4.0)]


def test_vector_functions(spark):
    from pyspark.sql import functions as F

    df = spark.createDataFrame([([1.0, 2.0], [3.0, 4.0], [[2.0, 1.0], [1.0, 3.0]])], "x array<double>, y array<double>, a array<array<double>>")
    x, y = F.col("x"), F.col("y")
    got = df.select(V.dot(x, y), V.norm(y), V.outer(x, y), V.quad(x, F.col("a")), V.add(x, y), V.subtract(x, y), V.scale(F.lit(2.0), x)).head()
    assert list(got) == [11.0, 5.0, [3.0, 4.0, 6.0, 8.0], 18.0, [4.0, 6.0], [-2.0, -2.0], [2.0, 4.0]]


@pytest.mark.parametrize("how", ["anti", "full"])
def test_overwriting_merge_truth_table(spark, how):
    old = spark.createDataFrame([(1, "a"), (2, "b"), (None, "n")], "k int, v string")
    new = spark.createDataFrame([(2, "B"), (3, "C"), (None, "N")], "k int, v string")
    got = sorted((r.k or 0, r.v) for r in overwrite_merge(old, new, ["k"], how=how).collect())
    assert got == [(0, "N"), (0, "n"), (1, "a"), (2, "B"), (3, "C")]
    assert overwrite_merge(old, new.limit(0), ["k"], how=how).count() == 3
    assert overwrite_merge(old.limit(0), new, ["k"], how=how).count() == 3


def test_merge_errors_and_relatives(spark):
    old = spark.createDataFrame([(1, "a")], "k int, v string")
    twice = spark.createDataFrame([(1, "x"), (1, "y")], "k int, v string")
    with pytest.raises(MergeError):
        overwrite_merge(old, twice, ["k"])
    with pytest.raises(MergeError):
        overwrite_merge(old, twice.withColumnRenamed("v", "w"), ["k"])
    assert rows(overwrite_merge(old, twice, ["k"], on_duplicate="last", order="v")) == [(1, "y")]
    assert append_merge(old, old).count() == 2 and distinct_merge(old, old).count() == 1
