"""The entry module without this subpackage, and the hashes and debts of single operators."""

import os
import shutil
import subprocess
import sys

import numpy as np
import pyarrow as pa

from graphblocks.llm import bpe, kernels, language_id, packing

ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def test_entry_loads_without_the_subpackage(tmp_path):
    for name in ("graphblocks", "__spark_entry__.py", "corpus_pipeline.py"):
        at = os.path.join(ROOT, name)
        (shutil.copytree if os.path.isdir(at) else shutil.copy)(at, tmp_path / name)
    shutil.rmtree(tmp_path / "graphblocks" / "llm")
    code = "import __spark_entry__ as e; q = e.queries(); assert 'pipeline' not in q and not any(x.startswith('op1_') for x in q) and len(q) > 100 and e.oracle_sql()"
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env=env)


def mirrored(n):
    """Two different strings of n letters whose sums modulo 2**64 are the same."""
    t = np.array([bin(i).count("1") & 1 for i in range(n)], np.uint8)
    return bytes(t + 97), bytes(98 - t)


def test_strings_with_equal_sums():
    a, b = mirrored(2048)
    data = np.frombuffer(a + b, np.uint8)
    starts, ends = np.array([0, 2048]), np.array([2048, 4096])
    sums = kernels.span_hash(kernels.prefix_hash(data), starts, ends)
    assert sums[0] == sums[1]
    words = kernels.word_hash(data, starts, ends)
    assert words[0] != words[1]
    model = bpe.model_of(bpe.tokenizer_json(None))
    rows = pa.array([a.decode(), b.decode()])
    got = [list(ids[bounds[k] : bounds[k + 1]]) for _, ids, bounds in model.encode_rows(rows) for k in range(len(bounds) - 1)]
    assert got == [list(model.encode_exactly(x.decode())) for x in (a, b)]


def test_rare_languages_keep_their_rows(spark):
    rows = [(i, f"common text number {i} of many", f"l{i % 9}") for i in range(9 * 800)] + [(10**6 + i, f"rare words stand here {i}", "rare") for i in range(120)]
    seen = {}
    fit = language_id.fit
    language_id.fit = lambda counts, languages, *a: seen.update(n={x: languages.count(x) for x in set(languages)}) or fit(counts[:50], languages[:50], 1)
    try:
        language_id.train(spark.createDataFrame(rows, "doc_id long, text string, lang string"), 2000)
    finally:
        language_id.fit = fit
    assert seen["n"]["rare"] == 120 and max(seen["n"].values()) <= 200


def test_sources_are_owed_for_blocks_without_them(spark):
    counts = [(b, "a", 100) for b in range(10)] + [(b, "b", 50) for b in (2, 9)]
    got = packing._sums_before(spark.createDataFrame(counts, "block long, source string, n long"))
    assert {(r["block"], r["source"]): r["before"] for r in got.collect()} == {**{(b, "a"): 100 * b for b in range(10)}, (2, "b"): 0, (9, "b"): 50}
