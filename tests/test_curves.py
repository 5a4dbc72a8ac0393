import numpy as np
import pytest
from pyspark.sql import functions as F

from knnscope.functions import curves


@pytest.mark.parametrize(("kind", "order"), [("hilbert", 3), ("z", 3), ("peano", 2)])
def test_keys_are_a_bijection_with_prefixes(kind, order):
    b = curves.base(kind)
    n = b**order
    x, y = curves.cells(kind, np.arange(n * n), order)
    assert (curves.keys(kind, x, y, order) == np.arange(n * n)).all()
    assert (curves.keys(kind, x // b, y // b, order - 1) == np.arange(n * n) // (b * b)).all()
    if kind != "z":
        assert (np.abs(np.diff(x)) + np.abs(np.diff(y)) == 1).all()


@pytest.mark.parametrize(("kind", "order"), [("hilbert", 4), ("z", 4), ("peano", 2)])
def test_columns_equal_arrays(spark, kind, order):
    n = curves.base(kind) ** order
    df = spark.range(n * n).select((F.col("id") % n).alias("cx"), F.floor(F.col("id") / n).cast("long").alias("cy"))
    got = df.select("cx", "cy", curves.key_column(kind, F.col("cx"), F.col("cy"), order).alias("key")).toPandas()
    assert (curves.keys(kind, got.cx, got.cy, order) == got.key).all()


def test_unknown_curve():
    with pytest.raises(ValueError):
        curves.base("moore")
