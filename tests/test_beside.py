"""Runs beside each other."""

import threading

import pytest

from coreset_spark.plans import workloads


def test_runs_go_on_beside_each_other_and_keep_their_order(spark):
    met = threading.Barrier(3)

    def run(i):
        met.wait(20)  # broken, where runs follow each other
        return -i

    assert workloads._beside(spark, run, [1, 2, 3]) == [-1, -2, -3]
    with pytest.raises(ZeroDivisionError):
        workloads._beside(spark, lambda i: 1 // i, [1, 0])
