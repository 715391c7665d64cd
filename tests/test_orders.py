import numpy as np
import pytest
from topomap.config import MapConfig, grid_from_density
from topomap.operators.ordering import order_staggered, start_index
from topomap.operators.train import iter_blocks


def by_pointers(n, passes):
    """The staggered order told by two closing end pointers and a direction, as an independent check of the closed form."""
    front, back, out = 0, n - 1, []
    for t in range(passes):
        at, step = (front, 1) if t % 2 == 0 else (back, -1)
        out.append([(at + step * j) % n for j in range(n)])
        if t % 2 == 0:
            front += 1
        else:
            back -= 1
    return out


@pytest.mark.parametrize("n", range(1, 31))
def test_closed_form_equals_pointers(n):
    assert [order_staggered(n, t).tolist() for t in range(n)] == by_pointers(n, n)


def test_worked_example_of_four():
    assert [order_staggered(4, t).tolist() for t in range(4)] == [[0, 1, 2, 3], [3, 2, 1, 0], [1, 2, 3, 0], [2, 1, 0, 3]]


@pytest.mark.parametrize("n", [1, 2, 7, 50, 99])
def test_every_sample_starts_once(n):
    assert sorted(start_index(t, n) for t in range(n)) == list(range(n))


@pytest.mark.parametrize("n,block", [(10, 3), (7, 7), (9, 1), (12, 5)])
def test_blocks_give_the_pass(n, block):
    for t in range(n):
        told = [i for lo, hi, step in iter_blocks(t, n, block) for i in range(lo, hi + step, step)]
        assert told == order_staggered(n, t).tolist()
        assert all(min(lo, hi) // block == max(lo, hi) // block for lo, hi, _ in iter_blocks(t, n, block))


def test_grid_from_density():
    assert grid_from_density(120, 10) == (4, 3)
    assert grid_from_density(110, 10) == (4, 3)
    assert grid_from_density(1, 10) == (1, 1)


def test_settings_are_checked():
    with pytest.raises(ValueError):
        MapConfig(stop="no_moves", max_passes=None)
    with pytest.raises(ValueError):
        MapConfig(init="random")
    with pytest.raises(ValueError):
        MapConfig(initial_rate=0)
    assert MapConfig(max_passes=5).resolved(100).horizon == 100


def test_dense_index_is_the_total_order(spark):
    from pyspark.sql import functions as F
    from topomap.operators.ordering import dense_index

    df = spark.range(0, 1000).select((F.col("id") * 7919 % 1000).alias("k")).repartition(7)
    rows = dense_index(df, ["k"]).collect()
    assert sorted((r["k"], r["sample_index"]) for r in rows) == [(i, i) for i in range(1000)]


def test_staggered_position_column(spark):
    from pyspark.sql import functions as F
    from topomap.operators.ordering import staggered_orders

    rows = staggered_orders(spark.range(9).withColumnRenamed("id", "sample_index"), 9, 9).orderBy("t", "position").collect()
    for t in range(9):
        assert [r["sample_index"] for r in rows if r["t"] == t] == order_staggered(9, t).tolist()
    assert np.unique([r["position"] for r in rows]).tolist() == list(range(9)) and F is not None
