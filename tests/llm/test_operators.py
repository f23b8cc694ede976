"""Corpus operators against brute force, exact round trips and held-out accuracy, and the defined odd cases."""

import hashlib
import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from evalengine.llm import (
    op1_byte_bpe,
    op2_quality_cotraining,
    op3_ngram_trie,
    op4_html_extraction,
    op5_curve_packing,
    op6_secret_scan,
    op7_iblt_fingerprint,
    op8_collision_dedup,
    op9_language_id,
    op10_ngram_jaccard,
)
from evalengine.llm._common import components, table

ODD = [(1, None, "en", "s", 0), (2, "", "en", None, 0), (3, "a b  c\n\n d\t e ", None, "s", None), (3, "a b  c\n\n d\t e ", None, "s", None), (None, "lost id", "en", "s", 7), (4, "x" * 3000, "en", "s", 3000), (5, "ß don't  stop now … 12", "de", "s", 9)]
COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, COLUMNS).withColumn("SCORE", F.lit("clash"))


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], COLUMNS)


@pytest.fixture(scope="module")
def docs(spark, small):
    return table(spark, small, "documents")


@pytest.fixture(scope="module")
def texts(docs):
    return {r.doc_id: r.text or "" for r in docs.select("doc_id", "text").collect()}


# op1


@pytest.fixture(scope="module")
def ranks():
    return op1_byte_bpe.read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken"))


def _tiktoken(ranks):
    import tiktoken

    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_op1_equals_the_library(spark, docs, odd, ranks):
    e = _tiktoken(ranks)
    for df in (docs, odd):
        want = Counter()
        for r in df.select("doc_id", "text").collect():
            ids = e.encode_ordinary(r.text or "")
            want[(r.doc_id, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((r.text or "").encode()).hexdigest())] += 1
        assert Counter(tuple(r) for r in op1_byte_bpe.encode(df, ranks, public_tokenizers.PATTERN).collect()) == want


def test_op1_native_fold_and_long_words(spark, ranks):
    e = _tiktoken(ranks)
    words = spark.createDataFrame([(w,) for w in ("the", " ththing", "entwicklung", "ciónes", "12", "!!", " zzqx")], "word string")
    for r in op1_byte_bpe.merge_words_native(words, ranks).collect():
        assert list(r.ids) == e.encode_ordinary(r.word)
    for w in ("ab" * 400, "thing" * 60):
        assert op1_byte_bpe.fold_merges(w.encode(), ranks) == e.encode_ordinary(w)


# op2, op9


def test_op2_finds_quality_of_documents_it_never_saw(spark, small, docs, odd, empty):
    labels = table(spark, small, "labels")
    unseen = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1
    model = op2_quality_cotraining.fit(docs, labels.where(~unseen))
    got = {r.doc_id: r for r in op2_quality_cotraining.score(docs, model).collect()}
    known = [(r.quality == 1) == got[r.doc_id].quality_keep for r in labels.where(unseen).collect() if r.doc_id in got]
    assert len(known) > 15 and np.mean(known) > 0.9
    # The combined score is what both views' calibrated logits say together.
    logit = lambda p: math.log(p / (1 - p))
    for r in list(got.values())[:50]:
        if 1e-6 < min(r.text_score, r.metadata_score) and max(r.text_score, r.metadata_score) < 1 - 1e-6:
            assert logit(min(max(r.quality_score, 1e-15), 1 - 1e-15)) == pytest.approx(logit(r.text_score) + logit(r.metadata_score) - model.prior, abs=1e-4)
    rows = op2_quality_cotraining.score(odd, model).collect()
    assert len(rows) == len(ODD) and all(0 <= r.quality_score <= 1 for r in rows) and {r.SCORE for r in rows} == {"clash"}
    assert op2_quality_cotraining.fit(empty, labels) is None
    clash = docs.limit(3).withColumn("Quality_Keep", F.lit("mine"))
    for m in (model, None):
        out = op2_quality_cotraining.score(clash, m)
        assert {"input_Quality_Keep", "quality_keep"} <= set(out.columns) and {r.input_Quality_Keep for r in out.collect()} == {"mine"}
    assert op2_quality_cotraining.score(empty, None).count() == 0


def test_op2_co_training_exchanges_sure_rows_only():
    rng = np.random.default_rng(0)
    y = np.arange(200) % 2 == 0
    view = lambda y, wide: y[:, None] * 2.0 + rng.standard_normal((len(y), wide))
    pool_y = np.arange(600) % 2 == 0
    pool = [view(pool_y, 2), view(pool_y, 3)]
    m = op2_quality_cotraining.co_train([view(y, 2), view(y, 3)], y, np.arange(200) % 3 == 0, pool, rounds=3, take=20)
    assert m.exchanged and all(0 < a <= 40 and 0 < b <= 40 for a, b in m.exchanged[:1])
    assert ((m.combined(pool) > 0.5) == pool_y).mean() > 0.9


def _plain_language_model(rows):
    """Word and n-gram counts by language as dictionaries; letters by Unicode category."""
    import regex

    words = lambda t: regex.findall(r"\p{L}+", (t or "").lower())
    langs = sorted({lang for _, lang in rows if lang is not None and any(words(t) for t, x in rows if x == lang)})
    counts = {x: Counter(w for t, lang in rows if lang == x for w in words(t)) for x in langs}
    grams = {x: [Counter() for _ in range(5)] for x in langs}
    for x in langs:
        for w, n in counts[x].items():
            framed = f"^{w}$"
            for k in range(1, 5):
                for i in range(len(framed) - k + 1):
                    grams[x][k][framed[i : i + k]] += 1 + math.log(n)

    def share(of, key):
        whole = set().union(*of)
        return [math.log((c[key] + 0.5) / (sum(c.values()) + 0.5 * len(whole))) for c in of] if key in whole else None

    def word(w):
        got = share([counts[x] for x in langs], w)
        if got:
            return got
        total, framed = [0.0] * len(langs), f"^{w}$"
        for i in range(len(framed)):
            for k in range(4, 0, -1):
                got = share([grams[x][k] for x in langs], framed[i : i + k]) if i + k <= len(framed) else None
                if got:
                    break
            else:
                singles = [grams[x][1] for x in langs]
                got = [math.log(0.5 / (sum(c.values()) + 0.5 * len(set().union(*singles)))) for c in singles]
            total = [a + b for a, b in zip(total, got, strict=True)]
        return [a / len(framed) for a in total]

    return langs, lambda t: [sum(c) for c in zip(*(word(w) for w in words(t)), strict=True)] if words(t) else None


def test_op9_equals_a_plain_model(spark):
    train = [("the cat and the dog; don't STOP", "en"), ("der Hund und die Katze Straße", "de"), ("le chat et le chien été", "fr"), ("und der", "de"), ("zz", None), (None, "en"), ("12 34", "xx")]
    frame = spark.createDataFrame([(i, t, x) for i, (t, x) in enumerate(train)], "doc_id long, text string, lang string")
    model = op9_language_id.fit(frame)
    langs, scores = _plain_language_model(train)
    assert model.langs == langs
    ask = ["the hound", "katzen und hunde", "chiens", "Größe", "qqq xyz", "\u00b2", "\u00bd 12 _", "", None, "été2fois", "der the", "x " * 20_000 + "und"]
    got = op9_language_id.predict(spark.createDataFrame([(i, t) for i, t in enumerate(ask)], "doc_id long, text string"), model).orderBy("doc_id").collect()
    for r in got:
        want = scores(r.text or "")
        if want is None:
            assert (r.lang_pred, r.score) == ("und", 0.0)
        else:
            top = max(want)
            assert r.lang_pred == langs[want.index(top)] or min(abs(top - w) for x, w in zip(langs, want, strict=True) if x == r.lang_pred) < 1e-3
            assert r.score == pytest.approx(1 / sum(math.exp(w - top) for w in want), abs=1e-3)


def test_op9_ties_do_not_depend_on_word_order(spark):
    train = [(0, "aa bb", "x"), (1, "bb aa", "y")]
    model = op9_language_id.fit(spark.createDataFrame(train, "doc_id long, text string, lang string"))
    asked = spark.createDataFrame([(i, t) for i, t in enumerate(["aa bb aa", "bb aa aa", "cc " * 999, "b a"])], "doc_id long, text string")
    assert {(r.lang_pred, r.score) for r in op9_language_id.predict(asked, model).collect()} == {("x", 0.5)}


def test_op9_held_out_accuracy_and_odd_texts(spark, small, odd, empty):
    rows = op9_language_id.op9_language_id(spark, small).join(table(spark, small, "documents").select("doc_id", "lang"), "doc_id").where("held_out AND lang_pred <> 'und'").collect()
    assert np.mean([r.lang == r.lang_pred for r in rows]) > 0.9
    model = op9_language_id.fit(table(spark, small, "documents"))
    got = [r.lang_pred for r in op9_language_id.predict(odd, model).orderBy(F.col("doc_id").asc_nulls_last()).collect()]
    out = op9_language_id.predict(odd, model)
    assert got[:2] == ["und", "und"] and all(0 <= r.score <= 1 for r in out.collect())
    assert "input_SCORE" in out.columns and {r.input_SCORE for r in out.collect()} == {"clash"}
    twice = [r.lang_pred for r in out.where("doc_id = 3").collect()]
    assert len(twice) == 2 and len(set(twice)) == 1
    assert {r.lang_pred for r in op9_language_id.predict(odd, op9_language_id.fit(empty)).collect()} == {"und"}
    assert op9_language_id.predict(empty, model).count() == 0


def test_op9_keeps_rare_languages(spark):
    letters = lambda i, k: "".join(chr(97 + i // k**j % k) for j in range(7))
    common = [(i, " ".join(letters(i * 41 + j, 12) for j in range(41)) * 2, "aa") for i in range(1200)]
    rare = [(5000 + i, f"zzyx wwvu qqzy{'z' * i}", "zz") for i in range(3)]
    docs = spark.createDataFrame(common + rare, "doc_id long, text string, lang string")
    model = op9_language_id.fit(docs, max_docs=1100)
    import pyarrow as pa

    held = model.words.find(op9_language_id.Spelled.of(pa.array(["zzyx", "wwvu", "qqzyzz"])).words())
    assert model.langs == ["aa", "zz"] and len(model.words.keys) > 40_000 and (held >= 0).all()
    assert {r.lang_pred for r in op9_language_id.predict(docs.where("doc_id >= 5000"), model).collect()} == {"zz"}
    assert op9_language_id.quota([10, 100, 1000], 300) == 190 and op9_language_id.quota([1, 2], 300) == 2


# op3


def test_op3_equals_a_plain_model(spark, small, texts):
    tok = lambda t: [w.encode().lower() for w in re.findall(r"[^\x20\x09-\x0D]+", t)] + [b"\0END"]
    toks = {i: tok(t) for i, t in texts.items()}
    held = {i: zlib.crc32(str(i).encode()) % 5 == 1 for i in toks}
    c, b, g = Counter(), Counter(), Counter()
    for i, t in toks.items():
        if not held[i]:
            c.update(t)
            b.update(zip(t, t[1:], strict=False))
            g.update(zip(t, t[1:], t[2:], strict=False))
    n, v, d = sum(c.values()), len(c), op3_ngram_trie.DISCOUNT
    new = min(0.5, max(sum(x == 1 for x in c.values()), 1) / n)
    back2, back3 = defaultdict(lambda: 1.0), defaultdict(lambda: 1.0)
    for (x, _), k in b.items():
        back2[x] -= (k - d) / c[x]
    for (x, y, _), k in g.items():
        back3[x, y] -= (k - d) / b[x, y]
    p1 = lambda w: c[w] / n * (1 - new) if c[w] else new
    p2 = lambda x, w: back2[x] * p1(w) + ((b[x, w] - d) / c[x] if (x, w) in b else 0) if x in back2 else p1(w)
    p3 = lambda x, y, w: back3[x, y] * p2(y, w) + ((g[x, y, w] - d) / b[x, y] if (x, y, w) in g else 0) if (x, y) in back3 else p2(y, w)
    rows = op3_ngram_trie.op3_ngram_trie(spark, small).collect()
    for r in rows:
        t = toks[r.doc_id]
        want = sum(math.log10(p1(w) if k == 0 else p2(t[k - 1], w) if k == 1 else p3(t[k - 2], t[k - 1], w)) for k, w in enumerate(t))
        assert r.score == pytest.approx(want, abs=3e-4 * len(t))
        assert r.base_score == pytest.approx(sum(math.log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in t), abs=1e-5)
        assert (r.n_tokens, r.n_known, r.train_tokens, r.held_out) == (len(t), sum(c[w] > 0 for w in t), n, held[r.doc_id])
    out = [r for r in rows if r.held_out]
    assert sum(r.score for r in out) > sum(r.base_score for r in out)


@pytest.mark.parametrize("n,top", [(0, 5), (1, 9), (50, 60), (1000, 2**50), (3000, 50_000), (5000, 2**63)])
def test_op3_successor_search_and_size(n, top):
    v = np.unique(np.random.default_rng(n).integers(0, top, n, dtype=np.uint64))
    held = op3_ngram_trie.EliasFano.arrays("x", v)
    m = op3_ngram_trie.EliasFano(held, "x")
    q = np.concatenate((np.random.default_rng(1).integers(0, top, 400, dtype=np.uint64), v, v + np.uint64(1)))
    i, hit = m.find(q)
    assert (hit == np.isin(q, v)).all()
    if len(v):
        assert (m.at(np.arange(len(v))) == v).all()
        assert (i == np.minimum(np.searchsorted(v, q), len(v) - 1)).all()


@pytest.mark.parametrize("top", [2**22, 2**40, 2**60])
def test_op3_sequences_are_as_small_as_the_code_allows(top):
    n = 200_000
    v = np.sort(np.random.default_rng(3).integers(0, top, n, dtype=np.uint64))
    held = op3_ngram_trie.EliasFano.arrays("x", v)
    assert sum(a.nbytes for a in held.values()) * 8 / n <= 1.25 * (2 + math.ceil(math.log2(top / n)))
    assert (op3_ngram_trie.EliasFano(held, "x").at(np.arange(n)) == v).all()


@pytest.mark.parametrize("v", [np.append(np.arange(500), 2**40), np.append(np.zeros(300), np.arange(3) + 2**50), np.arange(1000) * 7, np.sort(np.random.default_rng(6).integers(0, 90, 700)), np.array([5]), np.array([3] * 64 + [4] * 64 + [9])])
def test_op3_one_select_a_search(monkeypatch, v):
    m, asked, select = op3_ngram_trie.EliasFano(op3_ngram_trie.EliasFano.arrays("x", v.astype(np.uint64)), "x"), [0], op3_ngram_trie.EliasFano._select

    def counted(self, r, one):
        asked[0] += len(r)
        return select(self, r, one)

    monkeypatch.setattr(op3_ngram_trie.EliasFano, "_select", counted)
    q = np.concatenate((v, v + 1, [0])).astype(np.uint64)
    i, hit = m.find(q)
    assert (i == np.minimum(np.searchsorted(v.astype(np.uint64), q), len(v) - 1)).all() and (hit == np.isin(q, v.astype(np.uint64))).all()
    a, b = m.range(np.arange(len(v) - 1))
    assert (a == v[:-1].astype(np.uint64)).all() and (b == v[1:].astype(np.uint64)).all()
    if v[-1] < 10_000 and len(np.unique(v)) > 600:
        assert asked[0] == len(q) + len(a)


def test_op3_hot_words_over_many_shards_score_alike(spark, docs):
    slices = op3_ngram_trie.tokenised(docs.withColumn("held_out", F.col("doc_id") % 5 == 1))
    some = [op3_ngram_trie.learn(slices, n) for n in (op3_ngram_trie.TOKENS_A_SHARD, 300)]
    assert not some[0].hot and len(some[1].hot) > 3 and max(x[0] for x in some[1].hot.values()) > 2
    a, b = ({r.doc_id: r for r in op3_ngram_trie.score(slices, t).collect()} for t in some)
    for k, r in a.items():
        assert b[k].score == pytest.approx(r.score, abs=1e-3 * r.n_tokens) and b[k].n_known == r.n_known


def test_op3_copies_of_learned_texts_score_apart(spark):
    rng = np.random.default_rng(8)
    text = lambda: " ".join("".join(rng.choice(list("abcdefgh"), 5)) for _ in range(80))
    once = [text() for _ in range(60)]
    rows = [(i, False, t) for i, t in enumerate(once)] + [(100 + i, True, t) for i, t in enumerate(once[:20])] + [(200 + i, True, " ".join(rng.permutation(t.split()))) for i, t in enumerate(once[:20])]
    slices = op3_ngram_trie.tokenised(spark.createDataFrame(rows, "doc_id long, held_out boolean, text string"))
    per = {r.doc_id: r.score / r.n_tokens for r in op3_ngram_trie.score(slices, op3_ngram_trie.learn(slices)).collect()}
    assert min(per[100 + i] for i in range(20)) > max(per[200 + i] for i in range(20)) + 1


def test_op3_nothing_to_learn_and_odd_rows(spark, odd, empty):
    flagged = lambda df, held: op3_ngram_trie.tokenised(df.withColumn("held_out", F.lit(held)))
    trie = op3_ngram_trie.learn(flagged(empty, False))
    rows = op3_ngram_trie.score(flagged(odd, True), trie).collect()
    assert len(rows) == len(ODD) and all(r.score == 0 for r in rows)
    assert op3_ngram_trie.score(flagged(empty, False), trie).count() == 0
    own = flagged(odd, False)
    rows = {r.doc_id: r for r in op3_ngram_trie.score(own, op3_ngram_trie.learn(own)).collect()}
    assert rows[1].n_tokens == rows[2].n_tokens == 1 and rows[3].n_tokens == 6 and rows[None].n_tokens == 3 and all(r.score < 0 for r in rows.values())


# op4


def test_op4_held_out_layouts():
    model = op4_html_extraction.train(op4_html_extraction.labelled_pages())
    wrong = total = 0
    for page, mark in op4_html_extraction.labelled_pages(40, seed=5):
        nodes, truth = op4_html_extraction._labelled(page, mark)
        for node, b, y in zip(nodes, model.beliefs(nodes), truth, strict=True):
            total += bool(node.texts)
            wrong += bool(node.texts) and (b > 0.5) != bool(y)
    assert wrong < 0.03 * total


def test_op4_marginals_by_enumeration():
    import itertools

    unary, parent, tie = [0.3, -0.7, 1.1, 0.2], [-1, 0, 0, 1], (0.5, -0.4, -0.2, 0.9)
    z, hit = 0.0, np.zeros(4)
    for x in itertools.product((0, 1), repeat=4):
        w = math.exp(sum(u * v for u, v in zip(unary, x, strict=True)) + sum(tie[2 * x[parent[i]] + x[i]] for i in range(1, 4)))
        z += w
        hit += w * np.array(x)
    assert op4_html_extraction.marginals(unary, parent, tie)[0] == pytest.approx(hit / z)


def test_op4_pages_and_odd_html(spark, small):
    import html

    model = op4_html_extraction.train(op4_html_extraction.labelled_pages())
    pages = table(spark, small, "pages")
    got = {r.page_id: r.text for r in op4_html_extraction.extract(pages, model).collect()}
    for r in pages.collect():
        inside = re.search(r"<article>(.*?)</article>", r.html, re.S)[1]
        parts = (" ".join(html.unescape(re.sub(r"<[^>]*>", "", x.replace("<br>", " "))).split()) for x in re.split(r"</?(?:p|h1)[^>]*>", inside))
        assert got[r.page_id] == "\n".join(p for p in parts if p)
    odd = spark.createDataFrame([(1, "u", None), (2, "u", ""), (3, "u", "plain &amp; text"), (4, "u", "<p>open <b>tags"), (5, "u", "<script>x<p>"), (5, "u", "<!-- ")], "page_id long, url string, html string")
    assert [r.text for r in op4_html_extraction.extract(odd, model).orderBy("page_id").collect()][2] == "plain & text"


PARAGRAPHS = ["The first paragraph tells what happened in the town, and it goes on for some time.", "A second one follows, with names, places and a few more details of the matter.", "The third paragraph quotes a neighbour who saw it all from the window.", "Then the fourth one gives the history of the street, in two sentences. It is old.", "The last paragraph says what will be done about it next year."]


def test_op4_plain_layouts_and_comments_inside_articles():
    model = op4_html_extraction.train(op4_html_extraction.labelled_pages())
    ps, want = "".join(f"<p>{p}</p>" for p in PARAGRAPHS), "\n".join(PARAGRAPHS)
    nav, foot = '<nav><ul><li><a href="/">Home</a></li><li><a href="/a">About us</a></li></ul></nav>', "<footer><p>Copyright 2024 Example Press</p></footer>"
    said = '<div class="comment"><p>Nice text, thank you very much for it.</p></div><div class="comment"><p>I do not agree with this at all, sorry.</p></div>'
    for inside in (f"<div>{ps}</div>", ps, f"{nav}{ps}{foot}", f"{nav}<div>{ps}</div>{foot}", f'<article>{ps}<section class="comments">{said}</section></article>', f'{nav}<article>{ps}<div class="comments"><h3>Comments</h3>{said}</div></article>{foot}',
                   f'<div class="hdr"><a href="/">Home</a> <a href="/b">News</a></div><div class="xq17"><div class="r2">{ps}</div></div>{foot}', f'<table><tr><td class="menu"><a href="/">Home</a><a href="/x">X</a></td><td>{ps}</td></tr></table>',
                   f'{nav}<div id="wrapper"><div class="post">{ps}</div><div class="sidebar"><h4>Popular</h4><ul><li><a href="/1">One thing</a></li><li><a href="/2">Another</a></li></ul></div></div>{foot}'):
        assert op4_html_extraction.main_text(f"<html><body>{inside}</body></html>", model) == want, inside
    one = f'<html><body><div class="cookie-notice">We use cookies. Accept them?</div><div id="main"><p>{" ".join(PARAGRAPHS)}</p></div></body></html>'
    assert op4_html_extraction.main_text(one, model) == " ".join(PARAGRAPHS)


def test_op4_repeated_long_and_no_rows(spark):
    model = op4_html_extraction.train(op4_html_extraction.labelled_pages(40))
    long = "<html><body><article>" + "".join(f"<p>{p}</p>" for p in PARAGRAPHS * 3000) + "</article></body></html>"
    rows = [(1, "u", long, "x"), (2, None, "<p>same</p>", "x"), (2, None, "<p>same</p>", "x"), (None, "v", None, None)]
    frame = spark.createDataFrame(rows, "page_id long, url string, html string, TEXT string")
    got = op4_html_extraction.extract(frame, model).collect()
    assert sorted(str(r.page_id) for r in got) == ["1", "2", "2", "None"] and all(r.n_chars == len(r.text) for r in got)
    assert [r.text for r in got if r.page_id == 1] == ["\n".join(PARAGRAPHS * 3000)]
    assert op4_html_extraction.extract(frame.limit(0), model).count() == 0


# op5


def _library(path):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


def test_op5_ids_equal_the_library():
    import random

    import pyarrow as pa

    path, r = public_tokenizers.path("word_bpe_49k.json"), random.Random(4)
    library = _library(path)
    parts = ["'s", "'S", "'re", "'LL", "''t", "'", "a", "ab", "Zz", "é", "ÄÖ", "ß", "İ", "ſ", "ŉ", "Ÿ", "12", "²", "½", "ª", "!", "...", " ", "  ", "\n", "\t", "\r\n", "\xa0", "\xad", "\x1c", "\x85", "<|endoftext|>", "<|ENDOFTEXT|>", "中文", "🙂", "Σας", "ȺB", "e\u0301", "\u200b", "_x_", "don't", "thing" * 12, "q" * 70]
    texts = ["", " ", "'", "see <|endoftext|> here"] + ["".join(r.choice(parts) for _ in range(r.randint(1, 30))) for _ in range(3000)]
    ids, starts, _ = op5_curve_packing.coded(pa.array(texts), path)
    for i, t in enumerate(texts):
        assert ids[starts[i] : starts[i + 1]].tolist() == library.encode(t, add_special_tokens=False).ids, repr(t)


def test_op5_pieces_rebuild_every_document(spark, docs, odd, empty):
    path = public_tokenizers.path("word_bpe_49k.json")
    tok = _library(path)
    long = spark.createDataFrame([(77, "never ending <|endoftext|> story " * 30_000, "en", "s", 0)], COLUMNS)
    for df in (docs, odd.unionByName(long.withColumn("SCORE", F.lit("x")))):
        texts = {}
        for r in df.collect():
            texts.setdefault(r.doc_id, []).append(r.text or "")
        want = {k: np.array([*tok.encode(v[0], add_special_tokens=False).ids, 2], "<u4") for k, v in texts.items()}
        rows = op5_curve_packing.pack(df, path).collect()
        done, filled = Counter(), defaultdict(list)
        for r in rows:
            ids = want[r.doc_id]
            assert r.doc_tokens == len(ids) and zlib.crc32(ids[r.start : r.start + r.length].tobytes()) == r.ids_crc32
            done[r.doc_id] += r.length
            filled[r.sequence_id].append((r.offset, r.length))
        assert done == {k: len(v) * len(texts[k]) for k, v in want.items()}
        for parts in filled.values():
            at = 0
            for offset, length in sorted(parts):
                assert offset == at
                at += length
            assert at <= 4096
    assert op5_curve_packing.pack(empty, path).count() == 0


def test_op5_curve_visits_neighbours_and_clips_nothing():
    grid = np.array([[x, y] for x in range(8) for y in range(8)], float)
    unit = (grid + 0.5) / 4 - 1
    key = op5_curve_packing.hilbert_key(unit * op5_curve_packing.MIDDLE / (1 - np.abs(unit)), bits=3)
    assert set(np.abs(np.diff(grid[np.argsort(key)], axis=0)).sum(axis=1)) == {1.0}
    far = np.array([[x, 0.0, 0.0, 0.0] for x in (6.5, 9.0, 15.0, 40.0, 150.0)])
    assert len(set(op5_curve_packing.hilbert_key(far).tolist())) == len(far)


# op6


def test_op6_held_out_findings_and_redaction(spark, docs, odd):
    forest = op6_secret_scan.grown()
    found = op6_secret_scan.labelled_findings(400, seed=99)
    x = np.array([op6_secret_scan.describe(*f[:4]) for f in found])
    assert ((forest.predict(x) > 0.5) == np.array([f[4] for f in found])).mean() > 0.95
    planted = re.compile(r'token = "[0-9a-f]{40}"')
    clean = {r.doc_id: r.text for r in op6_secret_scan.redact(docs).collect()}
    assert not any(planted.search(t or "") for t in clean.values())
    changed = sum(clean[r.doc_id] != r.text for r in docs.collect())
    assert changed <= sum(bool(re.search(r"(?i)token = ", r.text or "")) for r in docs.collect())
    assert sorted(map(str, op6_secret_scan.redact(odd).collect())) == sorted(map(str, odd.collect()))


def test_op6_equals_row_by_row(spark, docs, odd, empty):
    forest = op6_secret_scan.grown()
    twice = "key token = \"" + "0a1b2c3d4e" * 4 + "\" end"
    extra = spark.createDataFrame([(901, twice, "en", "web", 1), (901, twice, "en", "web", 1), (902, "word " * 200_000 + twice, "en", None, 1)], COLUMNS)
    frame = docs.unionByName(extra).unionByName(odd.drop("SCORE"))
    want = Counter()
    for r in frame.collect():
        for a, b, kind, parts in op6_secret_scan.proposals(r.text or ""):
            s = max(float(forest.predict(np.array([op6_secret_scan.describe(r.text, x, y, r.source)]))[0]) for x, y in parts)
            want[r.doc_id, a, b - a, kind, round(s, 9), s >= 0.5, hashlib.sha256(r.text[a:b].encode()).hexdigest()] += 1
    got = Counter((r.doc_id, r.start, r.length, r.kind, round(r.score, 9), r.is_secret, r.value_sha256) for r in op6_secret_scan.scan(frame).collect())
    assert got == want and sum(n for (i, *_), n in want.items() if i == 901) == 2 and any(k[0] == 902 and k[1] > 900_000 and k[5] for k in want)
    assert op6_secret_scan.scan(empty).count() == 0 and op6_secret_scan.redact(empty).count() == 0


def test_op6_key_headers_without_an_end(spark):
    token = "9f8e7d6c5b" * 4
    body = "\n".join("Q2hhcmxpZSBiYWtlcnMgYXJlIGhlcmUgdG9kYXkgYW5k" for _ in range(3))
    head = "-----BEGIN RSA PRIVATE KEY-----"
    prose = " and then there is a lot of prose about the matter" * 12
    texts = [f'{head}{prose} api_key = "{token}" end', f"{head}\n{body}\n-----END RSA PRIVATE KEY-----\nafter it{prose}", f"{head}\n{body}\n{prose}"]
    docs = spark.createDataFrame([(i, t, "en", "web", len(t)) for i, t in enumerate(texts)], COLUMNS)
    clean = [r.text for r in op6_secret_scan.redact(docs).orderBy("doc_id").collect()]
    assert token not in clean[0] and prose in clean[0]
    assert "Q2hhcm" not in clean[1] and clean[1].endswith(f"after it{prose}")
    assert "Q2hhcm" not in clean[2] and prose in clean[2]


def test_op6_keys_without_digits_and_overlaps(spark):
    keys = ["AKIA" + "QWERTYUIOPASDFGH", "ghp_" + "aBcDeFgHiJkLmNoPqRsTuVwXyZaBcDeFgHiJ", "sk-live-" + "QwErTyUiOpAsDfGhJkLzXcVb", "AIza" + "SyAbCdEfGhIjKlMnOpQrStUvWxYzAbCdEfG"]
    texts = [f"see {k} here" for k in keys] + ['password="Ab!#c9d8e7f6g5h4i3j2k1"', "internationalization of src/main/resources/templates in snake_case_function_name"]
    docs = spark.createDataFrame([(i, t, "en", "web", len(t)) for i, t in enumerate(texts)], COLUMNS)
    clean = [r.text for r in op6_secret_scan.redact(docs).orderBy("doc_id").collect()]
    assert clean == ["see [SECRET] here"] * 4 + ['password="[SECRET]"', texts[5]]
    rows = op6_secret_scan.scan(docs).where("doc_id <= 4").orderBy("doc_id").collect()
    assert [(r.start, r.length, r.kind) for r in rows] == [(4, len(k), n) for k, n in zip(keys, ["cloud key", "code host token", "api key", "api key"], strict=True)] + [(10, 22, "assigned value")]


# op7


def test_op7_equals_sets(spark, docs, odd, empty):
    unit = lambda t: {u for u in re.split(op7_iblt_fingerprint.UNIT_END, t) if u}
    like = lambda a, b: 1 - len(a ^ b) / (len(a) + len(b)) if a or b else 1.0
    long = spark.createDataFrame([(77, " ".join(f"Sentence {i} of many." for i in range(30_000)), "en", "s", 0, "x"), (78, "a", "en", "s", 0, "x"), ((1 << 62) + 1, "big id", "en", "s", 0, "x"), ((1 << 62) + 3, "bigger id", "en", "s", 0, "x")], COLUMNS + ", SCORE string")
    last = -(1 << 62)
    whole = docs.withColumn("doc_id", F.col("doc_id") + 1000).withColumn("SCORE", F.lit("x")).unionByName(odd).unionByName(long)
    for df in (whole, docs.limit(1)):
        texts = [(last if r.doc_id is None else r.doc_id, r.text or "") for r in df.collect()]
        rows = sorted(texts, reverse=True)
        out = op7_iblt_fingerprint.fingerprints(df).collect()
        got = Counter((last if r.doc_id is None else r.doc_id, r.n_chars, r.edited_sha256, round(r.near_edited, 9), round(r.near_next, 9)) for r in out)
        want, by_text = Counter(), defaultdict(set)
        for k, (i, t) in enumerate(rows):
            following = rows[(k + 1) % len(rows)][1]
            edited = t[: len(t) - len(t) // 2] + following[: len(t) // 2]
            want[i, len(t), hashlib.sha256(edited.encode()).hexdigest(), round(like(unit(t), unit(edited)), 9), round(like(unit(t), unit(following)), 9)] += 1
        assert got == want
        for r in out:
            by_text[dict(texts)[last if r.doc_id is None else r.doc_id]].add(r.fingerprint)
        assert all(len(x) == 1 for x in by_text.values()) and len({min(x) for x in by_text.values()}) == len({frozenset(unit(t)) for t in by_text})
    assert op7_iblt_fingerprint.fingerprints(empty).count() == 0


def test_op7_retries_until_all_sketches_peel(spark):
    rows = [(i, [*range(i * 1000, i * 1000 + 40 + i)], [*range(i * 1000 + 20, i * 1000 + 90)], []) for i in range(60)]
    listed = spark.createDataFrame(rows, "row long, a array<bigint>, e array<bigint>, n array<bigint>").select("row", *(F.transform(c, lambda x: F.xxhash64(x)).alias(c) for c in "aen"))
    tight = op7_iblt_fingerprint.differences(listed, 0.02, 2)
    assert tight.where("left > 0").count() > 0
    op7_iblt_fingerprint.ROOM, kept = 0.02, op7_iblt_fingerprint.ROOM
    try:
        got = {r.row: r for r in op7_iblt_fingerprint.settled(listed, 2).collect()}
    finally:
        op7_iblt_fingerprint.ROOM = kept
    for i, a, e, n in rows:
        a, e, n = set(a), set(e), set(n)
        assert (got[i].gone0, got[i].new0, got[i].gone1, got[i].new1, got[i].left) == (len(a - e), len(e - a), len(a), 0, 0)


# op8, op10 and their graph


def test_components(spark):
    edges = [(i, i + 1) for i in range(20)] + [(100, 200), (200, 150), (7, 7), (None, 3)]
    got = {r.id: r.component for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(21)} | {100: 100, 150: 100, 200: 100}


def test_op8_equals_brute_force(spark):
    rng = np.random.default_rng(2)
    base = rng.standard_normal((40, 16))
    vectors = [v + rng.standard_normal(16) * s for v in base for s in (0, 0, 0.03, 0.06, 0.2)]
    rows = [(i, [float(x) for x in np.float32(v)], i % 2) for i, v in enumerate(vectors)]
    rows += [(900, None, 1), (901, [0.0] * 16, 1), (902, [float("nan")] * 16, 1), (903, rows[0][1], None), (904, rows[0][1][:8], 0), (905, [None] * 16, 0), (906, [], 0)]
    got = {r.vec_id: r for r in op8_collision_dedup.dedup(spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")).collect()}
    v = {i: (np.array(e, float), l) for i, e, l in rows[:200]}
    n, above = Counter(), {i: i for i, *_ in rows}

    def root(x):
        while above[x] != x:
            x = above[x]
        return x

    for i in v:
        for j in v:
            if i < j and v[i][1] == v[j][1] and v[i][0] @ v[j][0] / np.linalg.norm(v[i][0]) / np.linalg.norm(v[j][0]) >= 0.98:
                n[i] += 1
                n[j] += 1
                a, b = root(i), root(j)
                above[max(a, b)] = min(a, b)
    for i, *_ in rows:
        assert (got[i].n_links, got[i].component_id, got[i].kept) == (n[i], root(i), root(i) == i)


def test_op8_measured_recall_repeats_and_extreme_scales(spark, small):
    rows = [(r.vec_id, r.embedding, r.label) for r in table(spark, small, "embeddings").collect()]
    wide = len(rows[0][1])
    tiny, huge = [1e-46 * (i + 1) for i in range(wide)], [1e39 * (i + 1) for i in range(wide)]
    rows += [(90_001, tiny, 77), (90_002, huge, 77), (90_003, huge, 77), (90_003, huge, 77)]
    got = {}
    for r in op8_collision_dedup.dedup(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label long")).collect():
        got[r.vec_id] = r
    v = np.array([np.array(e, float) / np.abs(e).max() for _, e, _ in rows])
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    labels = np.array([l for *_, l in rows])
    links = (v @ v.T >= 0.98) & (labels[:, None] == labels[None, :])
    for k in range(0, len(rows), 20 if len(rows) > 3000 else 1):
        assert got[rows[k][0]].n_links == links[k].sum() - 1
    assert got[90_001].n_links == 3 and {got[i].component_id for i in (90_001, 90_002, 90_003)} == {90_001}
    empty = spark.createDataFrame([], "vec_id long, embedding array<double>, label long, N_LINKS string")
    assert op8_collision_dedup.dedup(empty).count() == 0


def test_op8_dense_chains_over_many_partitions(spark):
    step = math.radians(11)
    rows = []
    for c in range(40):
        for k in range(12):
            v = [0.0] * 12
            v[c % 10], v[c % 10 + 1] = math.cos(k * step / 2), math.sin(k * step / 2)
            rows.append((c * 100 + k, v, c))
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label long").repartition(16, "vec_id")
    for r in op8_collision_dedup.dedup(frame).collect():
        c, k = divmod(r.vec_id, 100)
        assert (r.n_links, r.component_id) == (sum(0 <= k + d < 12 for d in (-2, -1, 1, 2)), c * 100)


def test_op10_equals_brute_force(spark, texts, docs, odd, empty):
    sets = {}
    for i, t in texts.items():
        w = t.split()
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)}
    n, above = Counter(), {i: i for i in sets}

    def root(x):
        while above[x] != x:
            x = above[x]
        return x

    for i in sets:
        for j in sets:
            if i < j and 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]):
                n[i] += 1
                n[j] += 1
                a, b = root(i), root(j)
                above[max(a, b)] = min(a, b)
    for r in op10_ngram_jaccard.join(docs).collect():
        assert (r.n_links, r.class_id, r.kept) == (n[r.doc_id], root(r.doc_id), root(r.doc_id) == r.doc_id)
    assert op10_ngram_jaccard.join(odd).count() == len(ODD) and op10_ngram_jaccard.join(empty).count() == 0
    assert op10_ngram_jaccard.recall(0.8, 20, 4) > 0.9999


def test_op10_repeated_ids_keep_the_links_of_each_text(spark):
    rng = np.random.default_rng(11)
    a, b, c, d = (" ".join("".join(rng.choice(list("abcdefgh"), 6)) for _ in range(60)) for _ in range(4))
    rows = [(1, a), (2, a + " end"), (2, b), (2, b), (3, b + " end"), (4, c), (5, c), (6, d), (7, d + " end"), (2, None), (None, a)]
    got = op10_ngram_jaccard.join(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect()
    assert len(got) == len(rows)
    seen = {(r.doc_id, r.class_id, r.n_links, r.kept) for r in got}
    assert seen == {(1, 1, 1, True), (2, 1, 2, False), (3, 1, 1, False), (4, 4, 1, True), (5, 4, 1, False), (6, 6, 1, True), (7, 6, 1, False), (None, None, 0, True)}
