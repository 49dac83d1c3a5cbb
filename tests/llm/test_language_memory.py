"""Fitting the language model holds the sample's counts once."""

import tracemalloc

import numpy as np
import pyarrow as pa

from graphblocks.llm import language_id


def test_counts_are_held_once():
    r = np.random.default_rng(0)
    texts = ["".join(map(chr, r.integers(97, 110 + 8 * (i % 2), 200).tolist())) for i in range(1500)]
    langs = ["ab"[i % 2] for i in range(1500)]
    table = pa.table({"text": texts, "lang": langs})
    size = 1500 * language_id.CELLS * 4
    tracemalloc.start()
    counts, names = language_id.sample_counts(table)
    assert names == langs and (counts.sum(1) == 198).all()
    model = language_id.fit(counts, names, 20)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 1.6 * size
    assert model.languages == ["a", "b"]
