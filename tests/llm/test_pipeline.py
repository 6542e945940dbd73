"""The pipeline's stages against a plain replay of their decisions."""

import hashlib
from collections import Counter

import pytest

from pinflow.llm import mixing

corpus_pipeline = pytest.importorskip("corpus_pipeline")

from tests.llm.test_operators import lower, shingles  # noqa: E402


def test_stages(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["language_id", "exact_dedup", "minhash_near_dedup", "source_mixing", "bpe_encoding"]
    frames = [docs]
    for name, stage in corpus_pipeline.STAGES:
        frames.append(stage(spark, frames[-1], sf))
        if name != "bpe_encoding":
            assert frames[-1].columns == docs.columns
            frames[-1] = spark.createDataFrame(frames[-1].collect(), docs.schema)
    found = [{r["doc_id"]: r for r in f.collect()} for f in frames]
    every, spoken, single, apart, mixed, encoded = found
    assert all(any(c.isalpha() for c in every[i]["text"]) for i in spoken) and len(spoken) >= 0.97 * len(every)
    last = {}
    for i, r in spoken.items():
        last[lower(r["text"])] = max(i, last.get(lower(r["text"]), i))
    assert set(single) == set(last.values())
    sets = {i: shingles(r["text"]) for i, r in single.items()}
    label = {i: i for i in sets}
    by = {}
    for i, s in sets.items():
        for g in s:
            by.setdefault(g, []).append(i)
    links = {(a, b) for own in by.values() for a in own for b in own if a < b}
    links = [(a, b) for a, b in links if 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])]
    for _ in range(len(links) + 1):
        before = dict(label)
        for a, b in links:
            label[a] = label[b] = min(label[a], label[b])
        if before == label:
            break
    assert set(apart) == {i for i, c in label.items() if i == c}
    # Mixing is replayed in SQL on what the stage was given: the same documents, each as often.
    import duckdb

    frames[3].write.parquet(f"{tmp_path}/apart")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW apart AS SELECT * FROM read_parquet('{tmp_path}/apart/*.parquet')")
    want = dict(con.execute(mixing.oracle("apart", "doc_id, copies")).fetchall())
    drawn = Counter(r["doc_id"] for r in frames[4].collect())
    assert dict(drawn) == want and set(mixed) <= set(apart)
    assert all(mixed[i] == apart[i] for i in mixed)
    assert all(hashlib.sha256(mixed[i]["text"].encode()).hexdigest() == r["decoded_sha256"] for i, r in encoded.items()) and set(encoded) == set(mixed)
    assert {r["doc_id"] for r in corpus_pipeline.run(spark, sf).collect()} == set(encoded)


HOSTILE = "doc_id bigint, text string, lang string, source string, n_chars bigint, row int, mix_p double, `a.b` string, __id string"


def test_stages_on_hostile_rows(spark, sf):
    """Nulls in any column, empty texts, ties, repeated rows and clashing names: every stage ends and keeps the columns."""
    text = "the house and the water of the other thing in a house " * 3
    rows = [(i, f"{text} number {'abcdefghij'[i % 10]}", ["en", "de"][i % 2], "s", 5, 1, 0.5, "z", "q") for i in range(12)]
    rows += [(1, None, None, None, None, None, None, None, None), (None, text, "en", None, None, None, None, None, None), (None, None, None, None, None, None, None, None, None), (20, "", "en", "s", 0, 1, 0.5, "z", "q"), (21, "12 ²½ !?", "en", "s", 0, 1, 0.5, "z", "q"), rows[0], rows[0]]
    for data in (rows, rows[:1], []):
        docs = spark.createDataFrame(data, HOSTILE)
        for name, stage in corpus_pipeline.STAGES[:-1]:
            after = stage(spark, docs, sf)
            assert after.columns == docs.columns, name
            docs = spark.createDataFrame(after.collect(), docs.schema)
            if name == "language_id":
                assert docs.filter("text is null or text = '' or doc_id = 21").count() == 0
            if name == "exact_dedup":
                texts = [r["text"] for r in docs.collect()]
                assert len(texts) == len(set(texts))
        encoded = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
        assert encoded.count() == docs.count()
