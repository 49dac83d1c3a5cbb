"""The training-data operators against the library, brute force and SQL, with the awkward inputs."""

import hashlib
import json
import random
import zlib

import duckdb
import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from graphblocks.llm import bpe, jaccard_join, kernels, language_id, line_dedup, media, packing, quality_fm, quality_rules, queries, substring_dedup, suffix_dedup

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, tag string, doc string"


def awkward(seed=1, n=60):
    """Rows with nulls, empty and long texts, ties, repeated texts, near copies, shared passages."""
    r = random.Random(seed)
    words = [f"w{i}" for i in range(400)] + ["été", "Über", "A", "the", "is"]
    passage = " ".join(r.choice(words) for _ in range(40))
    texts = [None, "", " \t\n", "one", "One", "two words", "###", "\n\n", "x" * 700]
    for _ in range(n):
        t = " ".join(r.choice(words) for _ in range(r.randint(1, 120)))
        if r.random() < 0.4:
            cut = r.randint(0, len(t))
            t = t[:cut] + " " + passage + "\n" + t[cut:]
        texts.append(t)
        if r.random() < 0.3:
            w = t.split(" ")
            w[r.randrange(len(w))] = "changed"
            texts += [" ".join(w), t]
    texts.append(" ".join(r.choice(words) for _ in range(6000)) + " " + passage)
    r.shuffle(texts)
    return [(i * 3 + 1, t, "en" if i % 3 else None, None if i % 7 == 0 else f"s{i % 4}", None, "tag", "doc") for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def rows():
    return awkward()


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(5)


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)


def pairs(rows):
    return [(r[0], r[1]) for r in rows]


def tokenizer():
    import public_tokenizers as P
    from tokenizers import Tokenizer

    return Tokenizer.from_file(P.path("word_bpe_49k.json"))


ODD = ["", "'s", "''s", "it's don't we'll 'tis 'rest they're'", "!'s", "<|endoftext|>a", "a<|startoftext|>b <|x", "日本語 テスト", "ÀÉÎ İstanbul ΣΑΣ ς", "x" * 3000, "é á", "1234½²", "👍🏽 ok", "l'", "a\x1cb", "a\xa0b\x85c"]


def test_bpe_equals_library():
    from graphblocks.llm.common import tokenizer_json

    lib, own = tokenizer(), bpe.BpeModel(tokenizer_json(None))
    texts = ODD + [f"a{chr(c)}b {chr(c)}{chr(c)}1{chr(c)}'s{chr(c)}'ll X" for c in range(0x180)] + [r[1] or "" for r in awkward(2)]
    got = [ids[a:b] for _, ids, bounds in own.encode_rows(pa.array(texts)) for a, b in zip(bounds, bounds[1:])]
    for text, ids, e in zip(texts, got, lib.encode_batch(texts, add_special_tokens=False)):
        assert ids.tolist() == e.ids, text[:40]
        assert own.decode_bytes(ids).tobytes().decode() == lib.decode(e.ids, skip_special_tokens=False)


def test_bpe_rejects_unordered_merges():
    from graphblocks.llm.common import tokenizer_json

    spec = json.loads(tokenizer_json(None))
    spec["model"]["merges"][5], spec["model"]["merges"][9] = spec["model"]["merges"][9], spec["model"]["merges"][5]
    with pytest.raises(ValueError):
        bpe.BpeModel(json.dumps(spec).encode())


def test_bpe_query(docs, rows, nothing):
    lib = tokenizer()
    want = set()
    for d, t in pairs(rows):
        ids = lib.encode(t or "", add_special_tokens=False).ids
        want.add((d, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    assert {tuple(r) for r in bpe.bpe_digest(docs).collect()} == want
    assert bpe.bpe_digest(nothing).count() == 0
    back = bpe.bpe_decode(bpe.bpe_encode(docs.limit(5)))
    assert all(r["decoded"] == lib.decode(r["ids"], skip_special_tokens=False) for r in back.collect())


def brute_jaccard(rows):
    sets = {}
    for d, t in pairs(rows):
        low = (t or "").encode().translate(bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256)))
        w = low.split()
        sets[d] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    comp = {d: d for d in sets}
    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= 75 * (len(sets[a]) + len(sets[b]) - both):
                x, y = comp[a], comp[b]
                for k in comp:
                    if comp[k] in (x, y):
                        comp[k] = min(x, y)
    return {(d, len(sets[d]), comp[d]) for d in sets}


@pytest.mark.parametrize("block", [1024, 4])
def test_jaccard(docs, rows, nothing, monkeypatch, block):
    monkeypatch.setattr(jaccard_join, "BLOCK_ROWS", block)  # small blocks deal keys out
    assert {tuple(r) for r in jaccard_join.ngram_components(docs).collect()} == brute_jaccard(rows)
    assert jaccard_join.ngram_components(nothing).count() == 0


def test_jaccard_chain_without_a_common_leader(spark):
    w = [f"v{i}" for i in range(80)]
    texts = [" ".join(w[i : i + 60]) for i in (0, 6, 12, 18)]
    rows = [(i, t, None, None, None, "", "") for i, t in enumerate(texts)]
    got = {tuple(r) for r in jaccard_join.ngram_components(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got == brute_jaccard(rows) and {c for _, _, c in got} == {0}


def test_tree_finds_all_pairs():
    r = np.random.default_rng(1)
    points = r.integers(0, 3, (120, 16)).astype(np.int64)
    points[60:] = np.maximum(points[:60] - (r.random((60, 16)) < 0.05), 0)
    sizes = points.sum(1)
    got = {(min(a, b), max(a, b)) for x, y in jaccard_join.CountVectorTree(sizes, points).pairs() for a, b in zip(x.tolist(), y.tolist())}
    want = {(a, b) for a in range(120) for b in range(a + 1, 120) if 175 * np.minimum(points[a], points[b]).sum() >= 75 * (sizes[a] + sizes[b])}
    assert got == want and want


def test_substring(docs, rows, nothing):
    got = sorted(map(tuple, substring_dedup.digest(docs).collect()))
    assert got == sorted(substring_dedup.brute_force(pairs(rows), 13)) and sum(r[2] for r in got) > 0
    assert substring_dedup.digest(nothing).count() == 0
    out = substring_dedup.substring_dedup(docs, 7)
    assert out.columns[:5] == ["doc_id", "text", "lang", "source", "n_chars"]
    assert {r["doc_id"]: r["n_removed"] for r in out.collect()} == {r[0]: r[2] for r in substring_dedup.brute_force(pairs(rows), 7)}


def test_substring_with_equal_and_missing_ids(spark):
    t = " ".join(f"a{i}" for i in range(20))
    df = spark.createDataFrame([(1, t), (1, t), (1, t + " b"), (2, t), (None, t)], "doc_id long, text string")
    got = sorted((r["doc_id"] or 0, r["n_removed"]) for r in substring_dedup.substring_dedup(df).collect())
    assert got == [(0, 0), (1, 0), (1, 0), (1, 0), (2, 20)]


def test_suffix(docs, rows, nothing):
    got = sorted(map(tuple, suffix_dedup.digest(docs).collect()))
    assert got == sorted(suffix_dedup.brute_force(pairs(rows), 200)) and sum(r[2] for r in got) > 0
    assert suffix_dedup.digest(nothing).count() == 0
    short = suffix_dedup.suffix_dedup(docs, 40).select("doc_id", "n_removed", "n_spans")
    assert sorted(map(tuple, short.collect())) == sorted((d, r, s) for d, _, r, s, _ in suffix_dedup.brute_force(pairs(rows), 40))


def test_suffix_repeats_inside_a_text(spark):
    t = "".join(chr(97 + i * i % 26) for i in range(300)) * 3 + "tail"
    rows = [(1, t), (2, "é" * 150), (3, None)]
    got = sorted(map(tuple, suffix_dedup.digest(spark.createDataFrame(rows, "doc_id long, text string")).collect()))
    assert got == sorted(suffix_dedup.brute_force(rows, 200))


def test_rules(docs, rows, nothing, spark):
    got = {r["doc_id"]: r for r in quality_rules.digest(docs).collect()}
    con = duckdb.connect()
    import pandas as pd

    documents = pd.DataFrame(pairs(rows), columns=["doc_id", "text"])  # noqa: F841
    want = con.execute(quality_rules.SQL).df()
    assert len(want) == len(got)
    for r in want.to_dict("records"):
        assert {k: got[r["doc_id"]][k] for k in r} == r
    assert quality_rules.digest(nothing).count() == 0
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    j = quality_rules.quality_rules(spark.read.parquet(f"{SF}/documents.parquet")).join(labels, "doc_id").where("NOT base_failed").select("kept", "quality").toPandas()
    assert (j.kept == (j.quality == 1)).mean() > 0.95
    plan = quality_rules.digest(docs)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hash" not in plan and "Python" not in plan and "MapIn" not in plan


def test_media(docs, rows, nothing):
    got = {r["doc_id"]: r for r in media.media_digest(docs).collect()}
    for d, t in pairs(rows):
        b = (t or "").encode()
        p = b + b"\xff" * (max(576, -(-len(b) // 576) * 576) - len(b))
        r = got[d]
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(b), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-32:]))
        assert media.from_wav(media.to_wav(p)) == p and r["media_bytes"] == len(media.to_wav(p))
    assert media.media_digest(nothing).count() == 0
    row = media.media_columns(docs.where("length(text) > 3000")).first()
    assert media.text_payload(b"") == b"\xff" * 576 and len(row["peaks"]) and sorted(row["fingerprint"]) == row["fingerprint"]


def test_tone_gives_its_bin():
    t = np.arange(576 * 4)
    tone = (128 + 100 * np.sin(2 * np.pi * 40 * t / 576)).astype(np.uint8)
    assert (media.spectral_peaks(tone)[:, 0] == 40).all()


def test_classifier(spark, nothing):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    r = quality_fm.digest(docs, labels).join(labels, "doc_id").toPandas()
    held = r[r.held_out]
    assert (held.predicted == held.quality).mean() > 0.95 and r.score.between(0, 1).all()
    assert all((zlib.crc32(str(i).encode()) % 5 == 0) == h for i, h in zip(r.doc_id, r.held_out))
    assert quality_fm.digest(nothing, labels).count() == 0
    assert {x["score"] for x in quality_fm.digest(docs.limit(3), labels.limit(0)).collect()} == {0.5}


def test_pair_identity():
    r = np.random.default_rng(0)
    m = quality_fm.FactorMachine(0.1, r.normal(size=quality_fm.WORD_CELLS + quality_fm._N_STATS), r.normal(size=(quality_fm.WORD_CELLS + quality_fm._N_STATS, quality_fm.FACTORS)), np.zeros(quality_fm._N_STATS), np.ones(quality_fm._N_STATS))
    data = np.frombuffer(b"one two three! two\nTHREE | 4", np.uint8)
    parts = quality_fm.features(data, np.array([0, len(data)]))
    x = np.zeros(len(m.linear))
    x[parts[1]] = parts[2]
    x[quality_fm.WORD_CELLS :] = np.clip(parts[3][0], -6, 6)
    slow = m.constant + m.linear @ x + sum(m.factor[i] @ m.factor[j] * x[i] * x[j] for i in np.flatnonzero(x) for j in np.flatnonzero(x) if i < j)
    assert m.margin(*parts)[0] == pytest.approx(slow)


def test_languages(spark, docs, nothing):
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    r = language_id.digest(d).join(d.select("doc_id", "lang"), "doc_id").toPandas()
    held = r[r.held_out]
    assert (held.lang_pred == held.lang).mean() > 0.97 and r.score.between(0, 1).all()
    own = {x["doc_id"]: x for x in language_id.digest(docs).collect()}
    blank = [x["doc_id"] for x in docs.collect() if x["text"] is None or not any(c.isalpha() for c in x["text"])]
    assert all(own[i]["lang_pred"] == "und" and own[i]["score"] == 0 for i in blank) and len(own) == docs.count()
    assert language_id.digest(nothing).count() == 0


def test_codewords_are_apart():
    for n in (2, 4, 5, 9, 30):
        c = language_id.codebook(n)
        assert len(np.unique(c, axis=0)) == n
    assert int((language_id.codebook(4)[:, None] != language_id.codebook(4)[None]).sum(2)[np.triu_indices(4, 1)].min()) == 4


def lev(a, b):
    p = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        q = [i]
        for j, y in enumerate(b, 1):
            q.append(min(p[j] + 1, q[j - 1] + 1, p[j - 1] + (x != y)))
        p = q
    return p[-1]


def test_lines(spark, nothing):
    r = random.Random(4)
    base = [" ".join(r.choice("alpha beta gamma delta eps zeta eta theta iota kappa".split()) + str(r.randint(0, 60)) for _ in range(30)) for _ in range(25)]
    rows = []
    for i in range(60):
        ls = [r.choice(base) for _ in range(r.randint(0, 4))] + ["", "Short one!", f"unique {i}"]
        if r.random() < 0.5 and ls[0]:
            w = ls[0].split(" ")
            w[r.randrange(len(w))] = "zz"
            ls[0] = " ".join(w).upper()
        rows.append((i * 2, None if i == 7 else "\n".join(ls)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {x["doc_id"]: (x["n_lines"], x["n_removed"], x["text"]) for x in line_dedup.line_dedup(docs).collect()}
    sims = {x["norm"]: x["sim"] for x in line_dedup.with_simhash(line_dedup._lines(docs).withColumn("norm", line_dedup.normal_line(F.col("line")))).where("norm <> ''").select("norm", "sim").distinct().collect()}
    names = sorted(sims)
    group = {n: n for n in names}
    for i, a in enumerate(names):
        for b in names[i + 1 :]:
            if sims[a] is not None and sims[b] is not None and (sims[a] ^ sims[b]).bit_count() <= 2 and lev(a, b) <= max(len(a), len(b)) * 10 // 100:
                x, y = group[a], group[b]
                group = {n: (min(x, y) if g in (x, y) else g) for n, g in group.items()}
    norm = {(x["doc_id"], x["pos"]): x["norm"] for x in line_dedup._lines(docs).withColumn("norm", line_dedup.normal_line(F.col("line"))).collect()}
    seen = set()
    for d, t in rows:
        kept = []
        for pos, line in enumerate([] if t is None else t.split("\n")):
            g = group.get(norm[d, pos])
            if g is None or g not in seen:
                kept.append(line)
            if g is not None:
                seen.add(g)
        assert got[d] == (0 if t is None else len(t.split("\n")), 0 if t is None else len(t.split("\n")) - len(kept), None if t is None else "\n".join(kept))
    assert line_dedup.digest(nothing).count() == 0


@pytest.mark.parametrize("n", [7, 60, 600, 20000])
def test_simhash_is_the_majority(spark, n):
    norm = " ".join(f"t{i % 977}x{i % 31}" for i in range(n))
    row = line_dedup.with_simhash(spark.createDataFrame([(norm,)], "norm string")).first()
    h = np.array([x["h"] for x in spark.createDataFrame([(w,) for w in norm.split(" ")], "w string").select(F.xxhash64("w").alias("h")).collect()], np.int64).view(np.uint64)
    want = sum(1 << b for b in range(60) if 2 * int(((h >> np.uint64(b)) & np.uint64(1)).sum()) > n)
    assert (row["n"], row["sim"]) == (n, want)


def test_packing(docs, rows, nothing):
    lib = tokenizer()
    ids = {d: np.array(lib.encode(t or "", add_special_tokens=False).ids + [2], "<u4") for d, t in pairs(rows)}
    out = packing.pack(docs, width=256, block_tokens=2000).toPandas()
    for r in out.itertuples():
        x = ids[r.doc_id]
        assert r.doc_tokens == len(x) and zlib.crc32(x[r.start : r.start + r.length].tobytes()) == r.ids_crc32
    for d, g in out.sort_values("start").groupby("doc_id"):
        assert np.concatenate([np.arange(s, s + n) for s, n in zip(g.start, g.length)]).tolist() == list(range(len(ids[d])))
    for _, g in out.sort_values("offset").groupby("sequence_id"):
        assert np.concatenate([np.arange(s, s + n) for s, n in zip(g.offset, g.length)]).tolist() == list(range(g.length.sum()))
        assert g.length.sum() == 256 or (g.length.sum() & (g.length.sum() - 1)) == 0
    assert set(out.doc_id) == set(ids) and packing.pack(nothing).count() == 0


def test_packing_follows_the_mixture(spark):
    rows = [(i, " ".join(["word"] * 99), "big" if i % 3 else "small") for i in range(300)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    out = packing.pack(df, width=512, target={"big": 0.5, "small": 0.5}).toPandas()
    first = out[out.sequence_id < out.sequence_id.min() + 20]
    share = first.groupby("source").length.sum() / first.length.sum()
    assert abs(share["small"] - 0.5) < 0.02
    natural = packing.pack(df, width=512).toPandas()
    by = natural.pivot_table(index="sequence_id", columns="source", values="length", aggfunc="sum").fillna(0)
    full = by[by.sum(axis=1) == 512]
    assert (abs(full["small"] / 512 - 1 / 3) < 0.01).mean() > 0.9


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_sql_parity(spark, name):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{SF}/documents.parquet')")
    want = con.execute(queries.oracle_sql()[name]).df()
    got = queries.queries()[name](spark, SF).toPandas()[list(want.columns)]
    assert sorted(map(str, got.itertuples(index=False, name=None))) == sorted(map(str, want.itertuples(index=False, name=None)))


def test_kernels_chunk_any_batch():
    a = pa.array(["ab c", None, "", "  d\te "]).slice(0, 4)
    data, offsets = kernels.utf8_rows(a)
    starts, ends, first = kernels.word_spans(data, offsets)
    assert [bytes(data[s:e]) for s, e in zip(starts, ends)] == [b"ab", b"c", b"d", b"e"] and first.tolist() == [0, 2, 2, 2, 4]
    assert list(kernels.row_chunks(np.array([0, 5, 5, 50, 51]), 6)) == [(0, 2), (2, 3), (3, 4)]
