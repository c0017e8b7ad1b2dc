"""Results that lose nothing: parts of pages, languages, rows and minimisers that are easily left out."""

import random

import corpus_pipeline
import numpy as np
import pytest

from thriftline.llm import html_extract, substring_dedup

LONG = "word " * 60 + "end"
BREAK = "<nav>a</nav><nav>b</nav><nav>c</nav>"


@pytest.mark.parametrize("body, expected", [
    (f"<main><h1>Head</h1><article><p>{LONG}</p></article><p>Tail</p></main>", f"Head\n{LONG}\nTail"),
    (f"<article><p>{LONG}</p></article><article><p>{LONG} two</p></article>", f"{LONG}\n{LONG} two"),
    ("<div><p>Just a short page.</p></div>", "Just a short page."),
    (f"<div><p>{LONG}</p></div>{BREAK}<div><p>{LONG} two</p></div>", f"{LONG}\n{LONG} two"),
    (f"{BREAK}<div><p>{LONG}</p></div>{BREAK}", LONG),
])
def test_main_text_keeps_every_part(body, expected):
    assert html_extract.main_text(f"<html><body><nav><a>Home</a></nav>{body}<footer>us</footer></body></html>") == expected


def test_many_related_languages_lose_no_document(spark):
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randint(3, 7)))
    shared = [word() for _ in range(60)]
    rows = []
    for n in range(16):
        own = [word() for _ in range(40)]
        rows += [(20 * n + i, " ".join(rng.choice(shared if rng.random() < 0.6 else own) for _ in range(120)), f"l{n:02}") for i in range(8)]
    rows.append((999, "zq xj qz vq " + " ".join(word()[::-1] for _ in range(200)), None))
    # Two words of a language, often repeated, are still of that language.
    rows.append((1000, " ".join([own[0]] * 40 + [own[1]] * 40), "l15"))
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    kept = {r["doc_id"] for r in corpus_pipeline.keep_known_languages(spark, docs, "").collect()}
    assert kept == {i for i, _, lang in rows if lang}


def _two_texts(spark):
    rng = random.Random(5)
    words = lambda n: " ".join(f"w{rng.randrange(10**6)}" for _ in range(n))
    one, two, three = words(80), words(80), words(60)
    own, again = words(30), " ".join(one.split()[10:50])
    rows = [(7, one), (7, two), (7, one), (8, f"{own} {again}"), (9, three), (9, three)]
    return rows, own, spark.createDataFrame(rows, "doc_id long, text string").repartition(3)


def test_unrelated_texts_of_one_id_both_stay(spark):
    rows, _, docs = _two_texts(spark)
    kept = [tuple(r) for r in corpus_pipeline.drop_near_duplicates(spark, docs, "").collect()]
    assert sorted(kept) == sorted(set(rows))


def test_unrelated_texts_of_one_id_lose_no_words_to_each_other(spark):
    rows, own, docs = _two_texts(spark)
    got = sorted((r["doc_id"], r["text"]) for r in substring_dedup.substring_dedup(docs).collect())
    assert got == sorted((i, own if i == 8 else t) for i, t in rows)
    # Words of one text at the places of the repeat in another of the same id.
    first, second = f"{own} {own}", " ".join(f"v{i}" for i in range(60))
    rows = [(1, first), (1, second)]
    got = sorted(r["text"] for r in substring_dedup.substring_dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert second in got and any(len(t.split()) < 60 for t in got if t != second)


def test_minimisers_rare_in_each_batch_are_found_hot(spark, monkeypatch):
    monkeypatch.setattr(substring_dedup, "BUCKET_BYTES", 4096)
    rng = random.Random(6)
    same = " ".join(f"s{i}" for i in range(24))
    rows = [(f"{same} " + " ".join(f"x{rng.randrange(10**9)}" for _ in range(5)),) for _ in range(60)]
    docs = spark.createDataFrame(rows, "text string").repartition(20)
    hot, total, packed = substring_dedup._hot_minimisers(docs, 20, substring_dedup.MER)
    assert 0 < len(hot) <= packed // 1024 and total == sum(len(t) for t, in rows)
    assert len(np.unique(hot)) == len(hot)
