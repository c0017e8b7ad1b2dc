"""Small cases of every training-data operator: nulls, empty and long texts, ties, repeated rows, empty tables, clashing columns."""

import collections
import hashlib
import random
import zlib

import numpy as np
import pytest
from tests.llm import brute

from thriftline.llm import decontaminate, html_extract, language_id, near_dedup, packing, quality_classifier, quality_rules, sharding, substring_dedup, tokens
from thriftline.llm.queries import tokenizer_path

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, keys string, items string, score string, slot string, n_words string"


def corpus():
    rng = random.Random(3)
    words = [f"w{i}" for i in range(60)] + ["the", "of", "É", "naïve", "a,b", "字"]
    base = " ".join(rng.choice(words) for _ in range(120))
    near = base.split()
    near[5] = "changed"
    rows = [(0, base), (1, base), (2, " ".join(near)), (3, None), (4, ""), (5, " \n\t "), (6, "one two"), (7, "One  TWO"), (8, "one two three four")]
    rows += [(9, " ".join(rng.choice(words) for _ in range(40_000))), (10, base[:200] + " and then " + base[200:]), (11, "x\n" + base.upper())]
    rows += [(20 + i, " ".join(rng.choice(words) for _ in range(rng.randint(1, 80)))) for i in range(30)]
    rows += [(60 + i, " ".join([*base.split()[:40], *[rng.choice(words) for _ in range(30)]])) for i in range(6)]
    return rows


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, "en" if i % 2 else None, None, None, "k", "i", "s", "l", "n") for i, t in corpus()], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def nameless(spark):
    return spark.createDataFrame([(None, "some words that stand here twice " * 8, *["x"] * 2, 1, *["y"] * 5), (None, None, *[None] * 8), (5, "some words that stand here twice " * 8, *[None] * 8), (5, "some words that stand here twice " * 8, *[None] * 8)], SCHEMA)


def test_near_duplicates_equal_the_definition(docs):
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dedup.near_duplicates(docs).collect()}
    assert got == brute.near(corpus())
    five = {r["doc_id"]: r["component_id"] for r in near_dedup.near_duplicates(docs, 5, 80).collect()}
    assert five == {i: c for i, (_, c) in brute.near(corpus(), 5, 80).items()}


def test_near_duplicates_of_odd_tables(nothing, nameless):
    assert near_dedup.near_duplicates(nothing).count() == 0
    rows = near_dedup.near_duplicates(nameless).collect()
    assert len(rows) == 4
    assert all(r["kept"] and r["component_id"] is None for r in rows if r["doc_id"] is None)
    assert [r["component_id"] for r in rows if r["doc_id"] == 5] == [5, 5]


def test_large_groups_are_compared_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(near_dedup, "BLOCK", 8)
    rng = random.Random(8)
    base = [f"t{rng.randint(0, 999)}" for _ in range(90)]
    rows = []
    for i in range(60):
        own = list(base)
        for _ in range(rng.randint(0, 4)):
            own[rng.randrange(90)] = f"n{rng.randint(0, 99999)}"
        rows.append((i, " ".join(own)))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == brute.near(rows)


def test_rows_of_one_doc_id_are_told_apart_by_text(spark):
    rows = [(1, "a b c d e f"), (1, "u v w x y z"), (2, "u v w x y z"), (3, "A B C D E F"), (3, "other words stand here"), (1, "a b c d e f")]
    got = near_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted((r["doc_id"], r["component_id"], r["n_shingles"], r["kept"]) for r in got) == [(1, 1, 4, True), (1, 1, 4, True), (1, 1, 4, True), (2, 1, 4, False), (3, 1, 4, False), (3, 3, 2, True)]


def test_a_group_of_near_copies_is_sent_a_few_times_only(spark, monkeypatch):
    monkeypatch.setattr(near_dedup, "BLOCK", 16)
    monkeypatch.setattr(near_dedup.skewed, "LEAST", 50)
    monkeypatch.setattr(near_dedup.skewed, "PARTS", 4)
    rng = random.Random(12)
    base, rows = [f"t{i}" for i in range(300)], []
    for i in range(1200):
        own = list(base)
        own[rng.randrange(300)] = f"n{i}"
        rows.append((i, " ".join(own)))
    met = []
    rest = near_dedup._rest
    monkeypatch.setattr(near_dedup, "_rest", lambda *a: met.append(a[0].where("not main").count()) or rest(*a))
    got = {r["component_id"] for r in near_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    # All hang on the first center: no block meets another.
    assert got == {0} and met == [0]


def test_hot_keys_are_joined_whole(spark, monkeypatch):
    from thriftline.llm import skewed

    monkeypatch.setattr(skewed, "LEAST", 3)
    left = spark.createDataFrame([(k, i) for i, k in enumerate([1] * 9 + [2, 2, 3] + [None] * 4)], "k long, i long")
    right = spark.createDataFrame([(1, 9, "a"), (2, 2, "b"), (7, 0, "c")], "k long, w long, name string")
    assert sorted(r["i"] for r in skewed.joined(left, right, ["k"], "w", 16).collect()) == list(range(11))
    assert [r["name"] for r in skewed.joined(left, right, ["k"], "w", 16, outer=True).orderBy("i").collect()] == ["a"] * 9 + ["b"] * 2 + [None] * 5


def test_two_signatures_under_the_threshold_share_a_key():
    rng = np.random.default_rng(1)
    slots = rng.integers(0, 1 << 16, (50, near_dedup.SLOTS), dtype=np.uint16)
    other = slots.copy()
    for row in other:
        at = rng.choice(near_dedup.SLOTS, near_dedup.CHUNKS * (near_dedup.ERRORS + 1) - 1, replace=False)
        row[at] ^= 1
    a, b = near_dedup.index_keys(slots), near_dedup.index_keys(other)
    assert all(set(x) & set(y) for x, y in zip(a.tolist(), b.tolist(), strict=True))


def test_components_of_a_long_chain(spark):
    chain = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101)], "a long, b long")
    assert {r["node"]: r["component"] for r in near_dedup.smallest_reachable(chain).collect()} == {**dict.fromkeys(range(1, 41), 0), 101: 100}
    assert near_dedup.smallest_reachable(chain.limit(0)).count() == 0


def test_substring_dedup_equals_the_definition(docs):
    got = {r["doc_id"]: (r["n_words"], r["text"]) for r in substring_dedup.substring_dedup(docs).collect()}
    assert got == brute.substring(corpus())


def test_hot_minimisers_change_nothing(docs, monkeypatch):
    monkeypatch.setattr(substring_dedup, "HOT_LEAST", 1)
    monkeypatch.setattr(substring_dedup, "HOT_SHARE", 10**9)
    monkeypatch.setattr(substring_dedup, "BUCKET_BYTES", 2000)
    got = {r["doc_id"]: (r["n_words"], r["text"]) for r in substring_dedup.substring_dedup(docs).collect()}
    assert got == brute.substring(corpus())


def test_a_window_of_every_document_is_sent_once_a_task(monkeypatch):
    import types

    import pyarrow as pa

    monkeypatch.setattr(substring_dedup, "PIECE", 500)
    shared = " ".join(f"s{i}" for i in range(20))
    texts = [f"{shared} " + " ".join(f"d{n}x{i}" for i in range(30)) for n in range(100)]
    spans = substring_dedup.ts.Spans(*substring_dedup.ts.text_buffers(pa.array(texts))[:2], substring_dedup.ts.NON_SPACE)
    low = substring_dedup.Cut(spans, spans.hashes(), 20, 4).low
    hot = types.SimpleNamespace(value=np.unique(low))
    batch = pa.RecordBatch.from_arrays([pa.array(range(100)), pa.array(texts)], names=["doc_id", "text"])
    strings, gone = 0, 0
    for out in substring_dedup._send(20, 4, hot, 1)([batch]):
        for kind, block in zip(out.column(1).to_pylist(), out.column(2).to_pylist(), strict=True):
            ids, *_, text = substring_dedup._unpack(block, (np.int64, np.int32, np.int32))
            strings, gone = strings + (bytes(text).count(shared.encode()) if kind else 0), gone + (0 if kind else len(ids))
    assert strings == 1 and gone == 99


def test_substring_dedup_of_odd_tables(nothing, nameless):
    assert substring_dedup.substring_dedup(nothing).count() == 0
    rows = substring_dedup.substring_dedup(nameless).collect()
    text = "some words that stand here twice " * 8
    # A row without id loses nothing; a repeated row loses what repeats within the document only.
    assert sorted((r["doc_id"] or 0, r["n_removed"]) for r in rows) == [(0, 0), (0, 0), (5, 42), (5, 42)]
    assert {r["text"] for r in rows if r["doc_id"] is None} == {text.strip(), ""}


def test_sharding_is_minimax(docs):
    rows = sharding.shard_documents(docs, 5).collect()
    texts = dict(corpus())
    assert all(r["size"] == len((texts[r["doc_id"]] or "").encode()) + 8 and r["text_crc32"] == zlib.crc32((texts[r["doc_id"]] or "").encode()) for r in rows)
    shards = collections.defaultdict(list)
    for r in rows:
        shards[r["shard"]].append(r)
    assert all(sorted(x["slot"] for x in s) == list(range(len(s))) for s in shards.values())
    assert len({r["shard"] for r in rows if texts[r["doc_id"]] == texts[0]}) == 1
    groups = collections.Counter()
    for text in texts.values():
        key = int(hashlib.md5(("0" if text is None else "1" + text).encode()).hexdigest()[:15], 16)
        groups[key] += len((text or "").encode()) + 8
    sizes = [groups[k] for k in sorted(groups)]

    def shards_needed(capacity):
        n, held = 1, 0
        for size in sizes:
            if held + size > capacity:
                n, held = n + 1, 0
            held += size
        return n

    least = next(c for c in range(max(sizes), sum(sizes) + 1) if shards_needed(c) <= 5)
    assert max(sum(x["size"] for x in s) for s in shards.values()) == least


def test_cuts_do_not_depend_on_the_fan(spark, monkeypatch):
    rng = random.Random(4)
    keys = [rng.randrange(1 << 60) for _ in range(300)]
    rows = spark.createDataFrame([(k, rng.randint(1, 500)) for k in keys for _ in range(rng.randint(1, 3))], "key long, size long")
    wide = sharding.contiguous_cuts(rows, 7)
    monkeypatch.setattr(sharding, "FAN_BITS", 3)
    monkeypatch.setattr(sharding, "FAN", 8)
    assert sharding.contiguous_cuts(rows, 7) == wide


def test_a_hot_group_leaves_the_others_even(spark):
    rng = random.Random(11)
    rows = [(i, "copy " * 20) for i in range(900)] + [(1000 + i, f"own {i} " * rng.randint(1, 5)) for i in range(2000)]
    got = sharding.shard_documents(spark.createDataFrame(rows, "doc_id long, text string"), 6).groupBy("shard").sum("size").collect()
    sizes = sorted(r["sum(size)"] for r in got)
    assert len(sizes) == 6 and sizes[-1] == 900 * 108 and sizes[-2] <= 1.01 * sizes[0]


def test_sharding_of_odd_tables(nothing, nameless):
    assert sharding.shard_documents(nothing).count() == 0
    rows = sharding.shard_documents(nameless, 3).collect()
    assert len(rows) == 4 and all(r["law"] == "bytes" and r["grown_shard"] is None for r in rows)


PAGE = """<!DOCTYPE html><html><head><title>T</title><script>var x="</p>";</script></head><body class="has-sidebar"><nav><a>Home</a> <a>More</a></nav>
<div class="ad">Buy now</div>{body}<div id="comments"><p>{long}</p></div><form>name</form><footer>&copy; us</footer>"""


@pytest.mark.parametrize("body, expected", [
    ("<article><h1>A &amp; B</h1><p>Some <b>bold</b>\n text &lt;x&gt;.</p><p>{long}</p><p>End.</p></article>", "A & B\nSome bold text <x>.\n{long}\nEnd."),
    ("<div class='content'><h2>Head</h2><p>{long}</p><p>short</p><p>{long}&nbsp;z</p></div>", "Head\n{long}\nshort\n{long} z"),
    ("<article><p><b>open<br><p>{long}<p>last</article>", "open\n{long}\nlast"),
    ("<main><aside>note</aside><!-- <p>no</p> --><p>{long}</p><style>p{{}}</style></main>", "{long}"),
    ("", ""),
])
def test_main_text(body, expected):
    long = "word " * 60 + "end"
    page = PAGE.replace("{body}", body).replace("{long}", long).replace("{{}}", "{}")
    assert html_extract.main_text(page) == expected.replace("{long}", long)


def _simple(page):
    return page.replace("<article>", '<div class="post">').replace("</article>", "</div>")


def test_main_text_by_brute_force(spark, sf):
    pages = [r["html"] for r in spark.read.parquet(f"{sf.replace('0.001', '0.01')}/pages.parquet").collect()]
    for page in pages:
        assert html_extract.main_text(page) == brute.page_text(page, True)
        assert html_extract.main_text(_simple(page)) == brute.page_text(_simple(page), False)


def test_pages_without_article_give_the_same_text(spark, sf):
    pages = [r["html"] for r in spark.read.parquet(f"{sf.replace('0.001', '0.01')}/pages.parquet").collect()]
    same = sum(html_extract.main_text(page) == html_extract.main_text(_simple(page)) for page in pages)
    assert same >= 0.99 * len(pages)


@pytest.mark.parametrize("tag", sorted(html_extract.EMBEDDED))
def test_unclosed_elements_end_with_what_is_around_them(tag):
    long = "word " * 60 + "end"
    page = f"<html><body><article><p>one {long}</p><{tag}><path><p>two {long}</p><p>three</p></article><footer>us</footer>"
    assert html_extract.main_text(page) == f"one {long}\ntwo {long}\nthree"


@pytest.mark.parametrize("body, expected", [
    ("<article><p>{long}</p><div class='ad'>buy<p>two</p></article>", "{long}\ntwo"),
    ("<nav><a>x</a><article><p>{long}</p></article>", "{long}"),
    ("<article><div class='entry-header'><h1>Title</h1></div><header><h2>Sub</h2></header><p>{long}</p></article>", "Title\nSub\n{long}"),
    ("<article><p>{long}</p></article><section class='replies'><article class='comment'><p>Mine: {long}</p></article></section>", "{long}"),
    ("<div class='has-sidebar'><form><main><p>{long}</p></main></form></div>", "{long}"),
    ("<div><div><a>One</a></div><div><a>Two</a></div><div><a>Three</a></div></div><div><p>{long}</p><p>See <a>this</a>.</p></div>", "{long}\nSee this."),
    ("<p>{long}<svg width='1'/> after</p>", "{long} after"),
])
def test_main_text_of_awkward_pages(body, expected):
    long = "word " * 60 + "end"
    assert html_extract.main_text(f"<html><body>{body.replace('{long}', long)}</body></html>") == expected.replace("{long}", long)


def test_extraction_of_odd_tables(spark):
    schema = "page_id long, url string, html string, text string, n_chars string"
    pages = spark.createDataFrame([(1, "u", None, "t", "n"), (None, None, "", None, None), (2, "v", "<article><p>" + "é " * 300_000 + "</p>", None, None), (2, "v", "<p", None, None)], schema)
    rows = html_extract.extract(pages).collect()
    assert sorted(r["n_chars"] for r in rows) == [0, 0, 0, 599_999]
    assert html_extract.extract(pages.limit(0)).count() == 0


def _ids(texts):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
    return [[*e.ids, 2] for e in t.encode_batch([x or "" for x in texts], add_special_tokens=False)]


def test_packing_is_a_round_trip(docs):
    rows = packing.pack_documents(docs, tokenizer_path("word_bpe_49k.json"), tokens=256, segments=20).collect()
    expected = dict(zip((i for i, _ in corpus()), _ids([t for _, t in corpus()]), strict=True))
    pieces, sequences = collections.defaultdict(list), collections.defaultdict(list)
    for r in rows:
        ids = np.frombuffer(r["ids"], "<u4").tolist()
        assert len(ids) == r["length"] and r["doc_tokens"] == len(expected[r["doc_id"]])
        pieces[r["doc_id"]].append((r["start"], ids))
        sequences[r["sequence_id"]].append((r["offset"], r["length"]))
    assert {i: [x for _, ids in sorted(p) for x in ids] for i, p in pieces.items()} == expected
    for parts in sequences.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 256 and at & (at - 1) == 0 and len(parts) <= 20


def test_the_longest_that_fits_has_the_largest_dot_product():
    rng = random.Random(9)
    line, pool = packing.LinePool(), packing.Pool((512, 64, 512))
    for i in range(300):
        n = rng.randint(1, 400)
        line.add(i, n)
        pool.add(i, n, n)
    for room in (1, 7, 100, 399, 512):
        at = pool.best(np.array([room, 5, room], float))
        assert line.best(room) == (int(pool.vectors[at, 0]) if at >= 0 else 0)


def test_short_examples_are_packed_as_fast_as_long_ones():
    import time

    def rate(length):
        packer, n, begin = packing.Packer(4096, 1024, 4096), 1_200_000 // length, time.process_time()
        made = [s for i in range(n) for s in packer.add(i, length)] + list(packer.finish())
        assert sum(p[2] for s in made for p in s) == n * length
        # All but the sequences of what is left at the end of a pool are full.
        assert sum(sum(p[2] for p in s) < 4096 for s in made) <= 12
        return time.process_time() - begin

    assert rate(10) < 20 and rate(60) < 5


def test_packing_of_odd_tables(nothing, nameless):
    path = tokenizer_path("word_bpe_49k.json")
    assert packing.pack_documents(nothing, path).count() == 0
    rows = packing.pack_documents(nameless, path).collect()
    assert sum(r["length"] for r in rows) == 3 * len(_ids(["some words that stand here twice " * 8])[0]) + 1


def test_examples_keep_all_limits(spark):
    rng = random.Random(2)
    rows = [(i, rng.randint(1, 300), rng.randint(0, 150)) for i in range(500)] + [(900, None, None), (901, 5000, 1)]
    got = packing.pack_examples(spark.createDataFrame(rows, "example_id long, n_tokens int, n_loss int").coalesce(2), 512, 6, 256).collect()
    sizes = {i: (n or 0, k or 0) for i, n, k in rows}
    assert sorted(r["example_id"] for r in got) == sorted(sizes)
    held = collections.defaultdict(list)
    for r in got:
        if r["fits"]:
            held[r["sequence_id"]].append(r)
    assert [r["example_id"] for r in got if not r["fits"]] == [901]
    for rs in held.values():
        assert len(rs) <= 6 and sum(sizes[r["example_id"]][0] for r in rs) <= 512 and sum(sizes[r["example_id"]][1] for r in rs) <= 256
    assert len(held) <= 1.25 * max(sum(n for n, _ in sizes.values() if n <= 512) / 512, 502 / 6)


@pytest.mark.parametrize("name, drop", [("byte_bpe_50k.json", False), ("word_bpe_49k.json", True)])
def test_token_counts_equal_the_library(spark, name, drop):
    from tokenizers import Tokenizer

    rng = random.Random(5)
    parts = ["a", "B", "'s", "'ll", " ", "  ", "\n", "\t", ".", ",", "0", "12", "é", "Ç", "́", "字", " ", "…", "<|endoftext|>", "<|", "word", "don't"]
    parts += ["Привет", "мир", "ς", "İ", "ŉ", "。", "カ", "゛", "한", "ᄒ", "ᅡ", "क़", "न", "्", "ع", "َ", "😀", "\u3000", "\x85", "\x1c", "²", "ⅷ", "≠", "«", "\ufeff", "\u200b"]
    texts = [None, "", *("".join(rng.choice(parts) for _ in range(rng.randint(0, 30))) for _ in range(3000)), "long " * 60_000]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: (r["n_bytes"], r["n_tokens"], r["over_limit"]) for r in tokens.token_counts(rows, tokenizer_path(name), drop_space=drop).collect()}
    t = Tokenizer.from_file(tokenizer_path(name))
    sizes = [len(e) for e in t.encode_batch([x or "" for x in texts], add_special_tokens=False)]
    assert got == {i: (len((x or "").encode()), n, n > 512) for i, (x, n) in enumerate(zip(texts, sizes, strict=True))}


def test_what_is_remembered_is_bounded(monkeypatch):
    import pyarrow as pa

    encoder = tokens.Encoder(tokenizer_path("word_bpe_49k.json"), True, True)
    words = ["Привет, мир! " * 200, "字" * 5000, "λόγος και έργον " * 100]
    once = [r[2].tolist() for r in encoder.rows(pa.array(words))]
    assert encoder.count < 20 and encoder.total < 100
    monkeypatch.setattr(tokens, "KEPT_IDS", 5)
    assert [r[2].tolist() for r in encoder.rows(pa.array(words))] == once
    expected = [i for ids in _ids(words) for i in ids[:-1]]
    assert [i for block in once for i in block] == expected


def test_token_counts_of_odd_tables(nothing, nameless):
    path = tokenizer_path("byte_bpe_50k.json")
    assert tokens.token_counts(nothing, path).count() == 0
    assert tokens.token_counts(nameless, path).count() == 4


def test_forgetting_changes_nothing(spark, monkeypatch):
    import pyarrow as pa

    texts = pa.array([t for _, t in corpus()])
    path = tokenizer_path("byte_bpe_50k.json")
    whole = tokens.Encoder(path, False, False).counts(texts)
    monkeypatch.setattr(tokens, "KEPT", 10)
    few = tokens.Encoder(path, False, False)
    assert [few.counts(texts.slice(i, 1))[0] for i in range(len(texts))] == whole.tolist()


def test_rules_count_by_the_definition(spark, docs):
    rows = {r["doc_id"]: r for r in quality_rules.apply_rules(docs).collect()}
    for i, text in corpus():
        words = brute.SPACE.findall(text or "")
        lines = [x for x in (text or "").split("\n") if brute.SPACE.search(x)]
        times = collections.Counter(tuple(words[s : s + 8]) for s in range(len(words) - 7))
        hit = set()
        for s in range(len(words) - 7):
            if times[tuple(words[s : s + 8])] > 1:
                hit.update(range(s, s + 8))
        expected = (len(words), sum(map(len, words)), sum((text or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(hit), len(words) < 20 or 100 * len(hit) > 30 * len(words))
        assert tuple(rows[i][k] for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")) == expected
    plan = quality_rules.apply_rules(docs)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_rules_of_odd_tables(nothing, nameless):
    assert quality_rules.apply_rules(nothing).count() == 0
    assert quality_rules.apply_rules(nameless).where("base_failed").count() == 4


def test_grades_follow_the_ratings(spark):
    rng = random.Random(6)
    words = [f"w{i}" for i in range(300)]
    rows, labels = [], []
    for i in range(900):
        text = [rng.choice(words) for _ in range(rng.randint(20, 200))]
        grade = i % 3
        if grade == 0:
            text[rng.randrange(len(text))] = rng.choice(["vile", "foul"])
        if grade == 1:
            text = [w + "###" for w in text]
        rows.append((i, " ".join(text)))
        labels.append((i, int(grade == 2), int(grade == 0)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    known = spark.createDataFrame([x for x in labels if x[0] % 5], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r for r in quality_classifier.grade_documents(docs, known).collect()}
    held = [x for x in labels if not x[0] % 5]
    right = sum(got[i]["kept"] == (q == 1 and not t) for i, q, t in held)
    assert right >= 0.95 * len(held)
    assert all(got[i]["p_acceptable"] >= got[i]["p_good"] for i in got)
    again = {r["doc_id"]: r["expected_grade"] for r in quality_classifier.grade_documents(docs, known).collect()}
    assert again == {i: r["expected_grade"] for i, r in got.items()}


def test_grades_of_odd_tables(spark, nothing, nameless, docs):
    labels = spark.createDataFrame([(0, 1, 0), (2, 0, 1), (2, 1, 0), (None, 1, 1), (6, None, 0), (999, 1, 0)], "doc_id long, quality int, toxic int")
    assert quality_classifier.grade_documents(nothing, labels).count() == 0
    assert quality_classifier.grade_documents(docs, labels.limit(0)).where("kept and expected_grade is null").count() == docs.count()
    assert quality_classifier.grade_documents(docs, labels).count() == docs.count()
    assert quality_classifier.grade_documents(nameless, labels).count() == 4


def test_languages_on_held_out_documents(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = language_id.identify_languages(docs).join(docs.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in rows if r["held_out"]]
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in rows)
    assert sum(r["lang"] == r["lang_pred"] for r in held) >= 0.95 * len(held)
    assert all(0 <= r["score"] <= 1 for r in rows)


def test_scores_are_those_of_bundled_vectors():
    counts = {"x": np.zeros(language_id.SYMBOLS**3, np.int64), "y": np.zeros(language_id.SYMBOLS**3, np.int64)}
    rng = np.random.default_rng(2)
    for c in counts.values():
        c[rng.integers(0, len(c), 200)] = rng.integers(1, 50, 200)
    (langs, table), = language_id.score_tables(counts, seed=5)
    letters = np.random.Generator(np.random.PCG64(5)).choice(np.array([-1, 1], np.int8), (language_id.SYMBOLS, language_id.DIMENSIONS)).astype(np.int64)

    def vector(g):
        a, b, c = g >> 12, (g >> 6) & 63, g & 63
        return np.roll(letters[a], 2) * np.roll(letters[b], 1) * letters[c]

    prototypes = [sum(n * vector(g) for g, n in enumerate(counts[k]) if n) for k in langs]
    doc = rng.integers(0, len(table), 30)
    bundle = sum(vector(g) for g in doc)
    expected = [bundle @ p / np.linalg.norm(p) for p in prototypes]
    assert np.allclose(table[doc].sum(axis=0), expected, rtol=1e-3, atol=1e-1)


def test_profiles_are_those_of_all_training_rows(spark):
    rows = [("x", "abc abd"), ("y", "zzz é"), ("x", "abc"), ("y", ""), ("x", "字abc")]
    got = language_id.profiles(spark.createDataFrame(rows, "lang string, text string").repartition(3))
    import pyarrow as pa

    for lang in ("x", "y"):
        counts = np.zeros(language_id.SYMBOLS**3, np.int64)
        for _, _, gram, _ in language_id._grams(pa.array([t for k, t in rows if k == lang])):
            np.add.at(counts, gram, 1)
        own = language_id.bundle(counts)
        assert np.allclose(got[lang].bundle, own.bundle) and got[lang][1:] == own[1:]


@pytest.mark.parametrize("many", [2, 70])
def test_languages_by_brute_force(spark, many):
    rng = random.Random(many)
    word = lambda: "".join(rng.choice("abcdefghijklmnopqrstuvwxyzéñ") for _ in range(rng.randint(2, 6)))
    rows = []
    for n in range(many):
        own = [word() for _ in range(30)]
        rows += [(10 * n + i, " ".join(rng.choice(own) for _ in range(40)), f"l{n:03}") for i in range(4)]
    got = {r["doc_id"]: r for r in language_id.identify_languages(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    letters = language_id._letters(language_id.SEED).astype(np.int64)
    shape = language_id.symbols()

    def vector(text):
        s = [0, *(int(shape[ord(c)]) for c in text), 0]
        out = np.zeros(language_id.DIMENSIONS)
        for a, b, c in zip(s, s[1:], s[2:], strict=False):
            if (a or b) and (b or c):
                out += np.roll(letters[a], 2) * np.roll(letters[b], 1) * letters[c]
        return out

    bundles = {}
    for i, text, lang in rows:
        if zlib.crc32(str(i).encode()) % 5:
            bundles[lang] = bundles.get(lang, 0) + vector(text)
    for i, text, _ in rows[:: max(1, len(rows) // 8)]:
        own = vector(text)
        cosines = {k: own @ v / np.linalg.norm(own) / np.linalg.norm(v) for k, v in bundles.items()}
        assert got[i]["lang_pred"] == max(cosines, key=cosines.get)
        assert got[i]["score"] == pytest.approx(max(cosines.values()) / sum(max(c, 0) for c in cosines.values()), rel=1e-3)


def test_the_sample_is_bounded_in_bytes(spark):
    docs = spark.createDataFrame([(i % 40, f"word{i} good " * 50) for i in range(120)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(40)], "doc_id long, quality int, toxic int")
    full, few = quality_classifier.train(docs, labels), quality_classifier.train(docs, labels, sample_bytes=3000)
    assert full is not None and few is not None and quality_classifier.train(docs, labels, sample_rows=5) is not None


def test_grades_by_brute_force(spark):
    import math

    rows = [(1, "The good words, the good!"), (2, ""), (3, None), (4, "Bad ### words " * 30)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(1, 1, 0), (4, 0, 0), (2, 0, 1)], "doc_id long, quality int, toxic int")
    model = quality_classifier.train(docs, labels)
    got = {r["doc_id"]: r for r in quality_classifier.grade_documents(docs, labels).collect()}
    import pyarrow as pa

    for i, text in rows:
        (_, _, number, _), = quality_classifier.features(pa.array([text], pa.string()))
        score = sum(model.weights[k] for k in set(number.tolist()))
        tails = [1 / (1 + math.exp(-(score - t))) for t in model.thresholds]
        assert got[i]["p_acceptable"] == pytest.approx(tails[0]) and got[i]["p_good"] == pytest.approx(tails[1])
        assert got[i]["expected_grade"] == pytest.approx(sum(tails)) and got[i]["kept"] == (tails[1] >= 0.5)


def test_grades_rank_held_out_documents(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    held = labels.where("pmod(xxhash64(doc_id), 3) = 0")
    rows = quality_classifier.grade_documents(docs.join(labels.select("doc_id"), "doc_id", "left_semi"), labels.join(held, "doc_id", "left_anti")).join(held, "doc_id").collect()
    good = [r["expected_grade"] for r in rows if r["quality"] == 1 and not r["toxic"]]
    other = [r["expected_grade"] for r in rows if r["quality"] != 1 or r["toxic"]]
    assert good and other and sum((a > b) + 0.5 * (a == b) for a in good for b in other) >= 0.95 * len(good) * len(other)


def test_languages_of_odd_tables(spark, nothing, nameless):
    assert language_id.identify_languages(nothing).count() == 0
    rows = language_id.identify_languages(nameless).collect()
    assert len(rows) == 4 and all(r["lang_pred"] == "und" for r in rows)
    more = spark.createDataFrame([(i, t, lang) for i, (t, lang) in enumerate([("the cat and the dog", "en"), ("le chat et le chien", "fr"), ("12 34", "en"), (None, "fr"), ("", None)] * 12)], "doc_id long, text string, lang string")
    got = language_id.identify_languages(more).collect()
    assert all((r["lang_pred"] == "und") == (r["doc_id"] % 5 > 1) and (r["score"] > 0) == (r["doc_id"] % 5 < 2) for r in got)


ITEMS = [(1, None), (2, ""), (3, "!!"), (4, "Short item"), (5, "w1 w2 w3 w4 w5 w6 w7 w8 w9 w10 w11 w12"), (6, "w1 w2 w3 w4 w5 w6 w7 w8 w9 w10"), (7, "Naïve, naïve naïve"), (8, "lone"), (None, "w1")]


@pytest.mark.parametrize("size", [4 << 20, 30])
def test_decontamination_equals_the_definition(spark, size):
    rng = random.Random(7)
    pieces = [t for _, t in ITEMS if t] + ["w1 w2 w3", "Short", "item", "x-y", "w3 w4 w5 w6 w7 w8 w9 w10 w11 w12", "naïve"]
    rows = [(i, " ".join(rng.choice(pieces) for _ in range(rng.randint(0, 9)))) for i in range(80)] + [(200, None), (201, "w1 " * 50_000)]
    docs = spark.createDataFrame([(i, t, "c", "i") for i, t in rows], "doc_id long, text string, cover_0 string, items_0 string").repartition(3)
    items = spark.createDataFrame([(*x, 1) for x in ITEMS], "item_id long, text string, doc_id int")
    got = {r["doc_id"]: (r["n_words"], r["n_hit"], r["items"]) for r in decontaminate.decontaminate(docs, items, block_bytes=size).collect()}
    expected = brute.contaminated(rows, [x for x in ITEMS if x[0] is not None and x[1]])
    assert got == expected
    digests = {r["doc_id"]: r["items_sha256"] for r in decontaminate.decontaminate(docs, items).collect()}
    assert digests == {i: brute.sha(",".join(x)) for i, (_, _, x) in expected.items()}


def test_decontamination_of_odd_tables(spark, docs, nothing, nameless):
    items = spark.createDataFrame(ITEMS, "item_id long, text string")
    assert decontaminate.decontaminate(nothing, items).count() == 0
    assert decontaminate.decontaminate(docs, items.limit(0)).where("not contaminated and n_items = 0").count() == docs.count()
    assert decontaminate.decontaminate(nameless, items).count() == 4


def test_workers_let_go_of_encoders_that_a_task_has_not_asked_for():
    from thriftline.llm import tokens
    from thriftline.llm.arrowrun import give_back
    from thriftline.llm.queries import tokenizer_path

    path = tokenizer_path("word_bpe_49k.json")
    first = tokens.encoder_for(path, False, True)
    give_back()
    assert tokens.encoder_for(path, False, True) is first
    give_back()
    give_back()
    assert tokens.encoder_for(path, False, True) is not first
