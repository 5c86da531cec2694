"""Each stage of the pipeline, and the whole, against plain versions on a small table with odd rows."""

import random

import numpy as np
import pyarrow as pa
import pytest

import corpus_pipeline
from spanweave.llm import batches, language_id, near_duplicates, pii, tokens
from tests.llm.test_operators import ODD, brute_near, words

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(11)
    en, de = (["the", "and", "thing", "with", "other", "those"], ["und", "der", "schön", "nicht", "zeit", "über"])
    say = lambda w, n: " ".join(rng.choice(w) + rng.choice("abcdef") for _ in range(n))
    texts = [(say(en, 60), "en") for _ in range(12)] + [(say(de, 60), "de") for _ in range(12)]
    texts += [texts[0], (texts[1][0] + " tail", "en"), (texts[2][0].upper(), "en")]
    texts += [(t, None) for t in ODD] + [(f"{say(en, 30)} call +1 (017) 555-7713", "en")]
    return [(i, t, lang, "web", len(t or "")) for i, (t, lang) in enumerate(texts)]


@pytest.fixture(scope="module")
def bench(rows, spark, tmp_path_factory):
    folder = tmp_path_factory.mktemp("sf")
    leaked = rows[5][1][20:200]
    spark.createDataFrame([(0, leaked), (1, None), (2, "")], "item_id long, text string").coalesce(1).write.parquet(str(folder / "benchmark.parquet"))
    return str(folder)


def ids(df):
    return sorted(r["doc_id"] for r in df.collect())


def test_language_stage(spark, rows):
    docs = spark.createDataFrame(rows, SCHEMA)
    model = language_id.Model.fit([(t, lang) for _, t, lang, _, _ in rows if t is not None and lang])
    names, share = language_id.classify(model, [t for _, t, *_ in rows])
    want = {i: names[i] for i in range(len(rows)) if share[i] >= corpus_pipeline.LEAST_SHARE and share[i] > 0}
    got = corpus_pipeline.keep_language(spark, docs, "")
    assert got.columns == docs.columns and {r["doc_id"]: r["lang"] for r in got.collect()} == want
    assert set(range(24)) <= set(want) and 27 not in want and 28 not in want
    assert corpus_pipeline.keep_language(spark, docs.limit(0), "").count() == 0
    assert corpus_pipeline.keep_language(spark, docs.drop("lang"), "").count() == 0


def test_near_duplicates_stage(spark, rows):
    docs = spark.createDataFrame(rows, SCHEMA)
    want = sorted(i for i, (_, c) in brute_near([t for _, t, *_ in rows]).items() if i == c)
    got = corpus_pipeline.drop_near_duplicates(spark, docs, "")
    assert ids(got) == want and got.columns == docs.columns and 24 not in want and 26 not in want
    assert corpus_pipeline.drop_near_duplicates(spark, docs.limit(0), "").count() == 0


def test_benchmark_stage(spark, rows, bench):
    docs = spark.createDataFrame(rows, SCHEMA)
    assert ids(corpus_pipeline.drop_benchmark(spark, docs, bench)) == [i for i, *_ in rows if i != 5]
    assert corpus_pipeline.drop_benchmark(spark, docs.limit(0), bench).count() == 0


def test_private_stage(spark, rows):
    docs = spark.createDataFrame(rows, SCHEMA)
    want = {r["doc_id"]: r["text"] for r in pii.rewrite(docs).collect()}
    got = {r["doc_id"]: (r["text"], r["n_chars"]) for r in corpus_pipeline.hide_private(spark, docs, "").collect()}
    assert got == {i: (t, None if t is None else len(t)) for i, t in want.items()}
    assert "555-7713" not in want[len(rows) - 1] and all(want[i] == t for i, t, *_ in rows[:-1])


def test_packing_stage(spark, rows):
    docs = spark.createDataFrame(rows, SCHEMA)
    pieces = corpus_pipeline.pack(spark, docs, "").collect()
    size = {i: len(tokens.encode(t or "", tokens.default_path())) + 1 for i, t, *_ in rows}
    held = {i: np.zeros(n, int) for i, n in size.items()}
    for p in pieces:
        held[p["doc_id"]][p["start"] : p["start"] + p["length"]] += 1
    assert all((h == 1).all() for h in held.values())
    assert corpus_pipeline.pack(spark, docs.limit(0), "").count() == 0


def test_the_whole_pipeline(spark, rows, bench):
    """The stages one after the other by their plain versions: which documents reach the packing, and with how many ids."""
    spark.createDataFrame(rows, SCHEMA).coalesce(1).write.mode("overwrite").parquet(f"{bench}/documents.parquet")
    known = {r["doc_id"] for r in corpus_pipeline.keep_language(spark, spark.createDataFrame(rows, SCHEMA), "").collect()}
    left = [r for r in rows if r[0] in known]
    first = brute_near([t for _, t, *_ in left])
    left = [r for k, r in enumerate(left) if first[k][1] == k and r[0] != 5]
    hidden = {r["doc_id"]: r["text"] for r in pii.rewrite(spark.createDataFrame(left, SCHEMA)).collect()}
    got = {r["doc_id"]: r["doc_tokens"] for r in corpus_pipeline.run(spark, bench).collect()}
    assert got == {i: len(tokens.encode(t, tokens.default_path())) + 1 for i, t in hidden.items()}
    assert near_duplicates.WORDS == 5 and near_duplicates.PERCENT == 75


def test_slices_give_memory_back_after_each_batch(monkeypatch):
    calls = []
    monkeypatch.setattr(batches, "give_back", lambda: calls.append(1))
    one = pa.record_batch([pa.array(["ab", None, "cde", "f"])], names=["text"])
    assert [p.num_rows for p in batches.slices([one, one], limit=3)] == [2, 1, 1] * 2 and len(calls) == 2
