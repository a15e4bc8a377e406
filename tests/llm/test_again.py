"""Which signatures of the Jaccard join are looked at again."""

import numpy as np
import pyarrow as pa

from coreset_spark.llm import jaccard_join


def test_only_signatures_that_left_pairs_out_are_told_to_come_again():
    s = np.arange(1, 200, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    sketch = jaccard_join.sketch_of(s)
    keys = [5] * 4 + [9] * 2  # of four alike some pairs are left out where each sends one, of two none
    columns = {"key": keys, "i": [0] * 6, "j": [0] * 6, "side": [0] * 6, "class": [*range(6)], "root": [*range(6)], "size": [199] * 6, "sketch": [sketch] * 6}
    run = lambda most: {(r["a"], r["b"]): r["more"] for out in jaccard_join._open_pairs(jaccard_join.Join(), most)([pa.RecordBatch.from_pydict(columns)]) for r in out.to_pylist()}
    one, all_ = run(1), run(8)
    assert one[4, 5] is None and {v for k, v in one.items() if k != (4, 5)} == {5}
    assert len(all_) == 7 and set(all_.values()) == {None}
