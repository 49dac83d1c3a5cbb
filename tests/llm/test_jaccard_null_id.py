"""A copy without an id does not take the keys of one that has an id."""

import pyarrow as pa
import pytest

from graphblocks.llm import jaccard_join


def test_null_id_before_a_copy():
    class Levels:
        import numpy as np

        value = np.zeros(jaccard_join.SKETCH_CELLS, np.int64)

    t = " ".join(f"w{i}" for i in range(40))
    batch = pa.RecordBatch.from_arrays([pa.array([None, 7, 8], pa.int64()), pa.array([t, t, t])], ["doc_id", "text"])
    found = [d for out in jaccard_join._prefix_keys(Levels)(iter([batch])) for d in out.column(1).to_pylist()]
    assert set(found) == {7}


@pytest.mark.parametrize("first", [None, 1])
def test_near_copy_is_linked(spark, first):
    w = [f"w{i}" for i in range(60)]
    rows = [(first, " ".join(w)), (2, " ".join(w)), (3, " ".join([*w[:-1], "other"]))]
    df = spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)
    got = {r[0]: r[2] for r in jaccard_join.ngram_components(df).collect() if r[0] is not None}
    assert got[2] == got[3]
