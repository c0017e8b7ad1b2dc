"""The pipeline against plain definitions of its stages, and odd tables through every stage."""

import collections

import corpus_pipeline
import numpy as np
import pytest
from tests.llm import brute
from tests.llm.test_operators import _ids

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def test_stages_equal_their_definitions(spark, sf, tmp_path):
    docs, kept = spark.read.parquet(f"{sf}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, sf)
        out.write.parquet(str(tmp_path / name))
        kept[name] = docs = spark.read.parquet(str(tmp_path / name))
    texts = lambda df: {r["doc_id"]: r["text"] for r in df.collect()}
    first = texts(kept["language_id"])
    assert first == texts(spark.read.parquet(f"{sf}/documents.parquet"))
    classes = brute.near(list(first.items()), corpus_pipeline.SHINGLE, corpus_pipeline.PERCENT)
    second = texts(kept["near_dedup"])
    assert second == {i: t for i, t in first.items() if classes[i][1] == i}
    cut = brute.substring(list(second.items()))
    third = texts(kept["substring_dedup"])
    assert {i: t.split() for i, t in third.items()} == {i: t.split() for i, (_, t) in cut.items()}
    assert all(r["n_chars"] == len(r["text"]) for r in kept["substring_dedup"].collect())
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    found = brute.contaminated(list(third.items()), items)
    fourth = texts(kept["decontaminate"])
    assert fourth == {i: t for i, t in third.items() if not found[i][1]}
    assert kept["decontaminate"].columns == COLUMNS
    pieces = collections.defaultdict(list)
    for r in kept["packing"].collect():
        pieces[r["doc_id"]].append((r["start"], np.frombuffer(r["ids"], "<u4").tolist()))
    assert {i: [x for _, p in sorted(v) for x in p] for i, v in pieces.items()} == dict(zip(fourth, _ids(fourth.values()), strict=True))
    assert corpus_pipeline.run(spark, sf).count() == kept["packing"].count()


@pytest.mark.parametrize("name, stage", corpus_pipeline.STAGES)
def test_stages_take_odd_tables(spark, sf, name, stage):
    schema = "doc_id long, text string, lang string, source string, n_chars long, kept_text string"
    rows = [(None, None, None, None, None, None), (1, "", "en", "s", 0, ""), (2, "the words of a text " * 30, "en", "s", 600, "k"), (2, "the words of a text " * 30, "en", "s", 600, "k"), (3, "le mot et le texte " * 3000, "fr", None, None, None), (None, "the words here", "en", "s", 1, "k")]
    docs = spark.createDataFrame(rows, schema)
    out = stage(spark, docs, sf)
    empty = stage(spark, docs.limit(0), sf)
    assert empty.count() == 0
    got = out.collect()
    if name == "packing":
        assert sum(r["start"] == 0 for r in got) == len(rows)
    else:
        assert out.columns == docs.columns
        expected = {"language_id": 4, "near_dedup": 5}.get(name, 6)
        assert len(got) == expected
