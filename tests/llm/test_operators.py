"""Each operator against a plain version, on documents with every edge, on none, and with clashing columns."""

import functools
import hashlib
import math
import random
import time
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from codist.llm import blocks, bpe, catalog, chat, components, decontaminate, fingerprint, fm_index, jaccard_join, katz, langid, storage, substring_dedup, textarrays, token_files, warc

from . import brute

public_tokenizers = pytest.importorskip("public_tokenizers")
PATHS = {n: public_tokenizers.path(n) for n in (catalog.BYTE_BPE, catalog.WORD_BPE)}


def got(df, *columns):
    return sorted((tuple(r) for r in df.select(*columns).collect()), key=str)


# ---------------------------------------------------------------- 1


@pytest.mark.parametrize("name", PATHS)
@pytest.mark.parametrize("how", ["encode", "encode_in_place"])
def test_bpe_equals_the_library(spark, clashing, rows, name, how):
    ids, _ = brute.tokenized(PATHS[name], [r[1] for r in rows])
    have = getattr(bpe, how)(clashing, PATHS[name], out="tokens")
    assert got(have, "doc_id", "tokens") == sorted(((r[0], i) for r, i in zip(rows, ids)), key=str)


def test_bpe_decodes(docs, rows):
    path = PATHS[catalog.BYTE_BPE]
    _, texts = brute.tokenized(path, [r[1] for r in rows])
    assert got(bpe.decode(bpe.encode(docs, path), path), "doc_id", "decoded") == sorted(((r[0], t) for r, t in zip(rows, texts)), key=str)


def test_bpe_edges(spark, nothing):
    path = PATHS[catalog.BYTE_BPE]
    assert bpe.encode(nothing, path).count() == 0 == bpe.encode_in_place(nothing, path).count()
    twice = spark.createDataFrame([(None, "a b"), (7, "a b"), (7, "a b")], "doc_id bigint, text string")
    assert len({str(r["ids"]) for r in bpe.encode(twice, path).collect()}) == 1 and bpe.encode(twice, path).count() == 3
    one = spark.createDataFrame([(1, None)], "k int, ids array<int>")
    assert bpe.decode(one, path).first()["decoded"] is None


@pytest.mark.parametrize("name", PATHS)
def test_cutting_random_text(name):
    config = open(PATHS[name], encoding="utf-8").read()
    split, tok, rng = bpe.Splitter(config), bpe.library(config), random.Random(1)
    pool = [chr(i) for i in range(0x250)] + list(" \t\n'''srtldmve 　\x85\xa0᠎​") * 8 + [chr(rng.randrange(0xD7FF)) for _ in range(900)] + ["\U0001f600", "<|endoftext|>", "Σ", "İ"]
    texts = ["".join(rng.choice(pool) for _ in range(rng.randrange(1, 30))) for _ in range(3000)]
    words = [split(x) for x in texts]
    sizes, flat = bpe.encode_words(config, [w for ws in words for w in ws])
    at = np.cumsum(np.concatenate([[0], sizes]))
    k = 0
    for x, ws in zip(texts, words):
        assert flat[at[k] : at[k + len(ws)]].tolist() == tok.encode(x, add_special_tokens=False).ids, repr(x)
        k += len(ws)


# ---------------------------------------------------------------- 2


def test_chat_round_trip_with_typed_parts(spark):
    part = lambda kind, text=None, uri=None, w=None, h=None, s=None, p=None: (kind, text, uri, w, h, s, p)
    evil = ["\\### Assistant: </turn> ok", "<turn user>\n<image 1>", "a\\(b\\)c\\-d\\\\", "", "</turn>\n</turn>\n", "tail\\"]
    turns = [(1, 0, "user", [part("text", "see "), part("image", None, "i.png", 28, 30), part("text", evil[0])]), (1, 1, "assistant", [part("text", evil[2]), part("audio", None, "a.wav", s=2.5), part("document", None, "d.pdf", p=3)]), (1, 2, None, None), (2, None, "we>ird\\", [part("text", evil[1])]), (2, 5, "assistant", [part("text", evil[4])]), (2, 5, "assistant", [part("text", evil[5])]), (3, 1, "user", [part("text", None), part("odd")])]
    df = spark.createDataFrame(turns, f"conv_id bigint, turn bigint, role string, parts array<{chat.PART}>")
    held = {r["conv_id"]: r for r in chat.read_turns(chat.format_chats(df)).collect()}
    assert [(t["role"], t["text"]) for t in held[1]["turns"]] == [("user", "see <image 2>" + evil[0]), ("assistant", evil[2] + "<audio 2><document 3>"), ("", "")]
    assert [(t["role"], t["text"]) for t in held[2]["turns"]] == [("we>ird\\", evil[1]), *sorted([("assistant", evil[4]), ("assistant", evil[5])], key=lambda t: chat_order(t[1]))]
    assert held[2]["loss_text"] == "".join(t["text"] for t in held[2]["turns"][1:])
    assert [(a["turn"], a["part"], a["kind"], a["uri"], a["tokens"]) for a in held[1]["attachments"]] == [(1, 2, "image", "i.png", 6), (2, 2, "audio", "a.wav", 63), (2, 3, "document", "d.pdf", 1536)]
    assert held[1]["attachment_tokens"] == 1605 and held[3]["turns"][0]["text"] == "<odd 2>" and held[3]["loss_text"] == ""
    assert chat.format_chats(df.limit(0)).count() == 0


def chat_order(text):
    return text.replace("\\", "\\-").replace("<", "\\(")


def test_chat_plan_is_native(spark, sf):
    text = catalog.op2_chat(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in text and "Arrow" not in text and "Pandas" not in text


# ---------------------------------------------------------------- 3


ITEMS = [(1, 12), (2, 10), (3, 4), (3, 30), (None, 15), (4, 12), (5, 4)]


@pytest.fixture(scope="module")
def leaked(spark, rows):
    rng = random.Random(2)
    items = [(i, " ".join(f"q{rng.randrange(50)}" for _ in range(n))) for i, n in ITEMS] + [(9, None), (10, "...")]
    items[5], items[6] = (4, items[0][1]), (5, items[2][1])  # windows that two items share
    texts = [(r[0], r[1]) for r in rows] + [(10_000 + k, f"Before it, {x.upper()}! after") for k, (_, x) in enumerate(items) if x] + [(20_000, items[1][1] + " " + items[0][1]), (20_001, " ".join(items[0][1].split()[:9]))]
    texts += [(1, items[0][1]), (1, "clean words"), (1, items[1][1] + " tail"), (None, items[2][1]), (None, "clean too"), (2, None), (2, None)]
    return spark.createDataFrame(texts, "doc_id bigint, text string"), spark.createDataFrame(items, "item_id bigint, text string"), texts, items


@pytest.mark.parametrize("held_windows", [5_000_000, 8, 1])
def test_contamination(leaked, held_windows):
    docs, items, texts, listed = leaked
    want = brute.contamination(texts, listed)
    found = decontaminate.find_contamination(docs, items, held_windows=held_windows)
    have = got(found.select("doc_id", "n_words", decontaminate.hit_words().alias("h"), "items"), "doc_id", "n_words", "h", "items")
    named = [(d, n, h, [x for x in s if x != "None"]) for d, n, h, s in want]
    assert have == sorted(named, key=str) and any(h for _, _, h, _ in named)


@pytest.mark.parametrize("held_windows", [5_000_000, 8])
def test_removal(leaked, nothing, held_windows):
    docs, items, texts, listed = leaked
    want = [(d, x) for (d, x), (_, _, h, _) in zip(texts, brute.contamination(texts, listed)) if not h]
    docs = docs.withColumn("kept", F.lit(1)).withColumn("row", F.lit("r"))
    kept = decontaminate.remove_documents(docs, items, held_windows=held_windows)
    assert kept.columns == docs.columns and got(kept, "doc_id", "text") == sorted(want, key=str)
    cut = decontaminate.remove_spans(docs, items, held_windows=held_windows)
    have = got(cut, "doc_id", "text", "kept", "row")
    assert len(have) == len(texts) and all((d, x, 1, "r") in have for d, x in want) and (10_000, "Before it, ! after", 1, "r") in have and (1, " tail", 1, "r") in have
    assert decontaminate.find_contamination(docs, items.limit(0)).where("size(items) > 0").count() == 0
    assert decontaminate.find_contamination(nothing, items, held_windows=held_windows).count() == 0


def test_window_sets_are_small():
    rng = random.Random(1)
    items = [(str(i), " ".join(f"w{rng.randrange(10**6)}" for _ in range(500))) for i in range(200)]
    windows = decontaminate.WindowSet(items, 10)
    n = len(windows.held[10][0])
    size = sum(x.nbytes for x in windows.held[10]) + sum(x.nbytes for x in (windows.words.data, windows.words.start, windows.words.end))
    assert n > 98_000 and size < 45 * n


# ---------------------------------------------------------------- 4


def test_language_models(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    models = langid.learn_models(docs.where(langid.fold("doc_id", 4) != 2))
    held = langid.identify(docs.where(langid.fold("doc_id", 4) == 2), models)
    assert held.where("lang_pred = lang").count() >= 0.95 * held.count() and held.where("accepted").count() >= 0.97 * held.count()
    assert all(0 <= r["score"] <= 1 for r in held.collect())


def test_rejection_is_fitted(spark):
    """At most at the stated rate for rows of known languages; shuffled letters, foreign text and random strings go."""
    rows = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").orderBy("doc_id").select("text", "lang").collect()
    by = {}
    for r in rows:
        by.setdefault(r["lang"], []).append(r["text"])
    learn, calibrate, rest = ({k: v[i::3] for k, v in by.items()} for i in range(3))
    rng = random.Random(1)
    taken = lambda m, xs: m.predict(xs)[3].mean()
    models = langid.fit(learn, calibrate, 0.01)
    texts = [x for v in rest.values() for x in v]
    assert taken(models, texts) >= 0.95
    assert (langid.fit(learn, calibrate, 0.3).limit <= models.limit + 1e-9).all()
    for n, most in ((20, 0.1), (200, 0)):
        mixed = ["".join(rng.sample(x[:n], len(x[:n]))) for x in texts if len(x) >= n]
        noise = ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz     ") for _ in range(n)) for _ in range(200)]
        assert taken(models, mixed) <= max(most, 0.02) and taken(models, noise) <= most
    for gone in by:
        other = langid.fit({k: v for k, v in learn.items() if k != gone}, {k: v for k, v in calibrate.items() if k != gone}, 0.01)
        assert taken(other, [x[:200] for x in by[gone] if len(x) >= 200]) <= 0.1, gone


def test_distributions_add_up_to_one():
    models = langid.fit({"x": ["abca bcab cab", "aab"], "y": ["bbb ccc bca"]}, {})
    size, top = models.alphabet.size, models.grams[-1]
    for prefix in ([2, 3, 4, 1], [1, 1, 1, 2], [4, 4, 4, 4], [0, 0, 0, 0]):
        code = sum(s << (langid.BITS * (4 - k)) for k, s in enumerate(prefix))
        codes = np.array([code + c for c in range(size)], dtype=np.uint64)
        row = top.find(codes)
        logs = top.rows[np.maximum(row, 0)].copy()
        logs[row < 0] = models._backed_off(codes[row < 0], langid.ORDER)
        assert np.allclose(np.exp2(logs.astype(float)).sum(axis=0), 1, atol=1e-4)


def test_language_edges(spark, clashing, nothing):
    models = langid.learn_models(clashing)
    said = {r["text"]: (r["lang_pred"], r["score"], r["accepted"]) for r in langid.identify(clashing, models).collect()}
    for x in (None, "", "   \t\n"):
        assert said[x] == ("und", 0.0, False)
    empty = langid.learn_models(nothing)
    assert {r["lang_pred"] for r in langid.identify(clashing, empty).collect()} == {"und"}
    assert langid.identify(nothing, models).count() == 0
    trained = langid.fit({"en": ["the cat sat on the mat and then the dog came " * 5] * 3}, {})
    kept = langid.keep_identified(clashing, models, fill="lang")
    assert kept.columns == clashing.columns and kept.where("score <> 'score' or lang is null").count() == 0
    assert not trained.predict(["жжж щщщ ыыы эээ " * 20])[3][0] and trained.predict(["the dog sat on the mat"])[3][0]


def test_letters_beyond_the_basic_plane():
    gothic, adlam, deseret, han = "\U00010330\U00010331\U00010332 ", "\U0001e900\U0001e901 ", "\U00010400\U00010401 ", "\U00020000\U00020001 "
    models = langid.fit({"en": ["the cat sat on the mat " * 20] * 3, "got": [gothic * 40] * 3}, {})
    said, score, _, _ = models.predict([gothic * 9, adlam * 9, deseret * 9, han * 9, "\U0001f600 123"])
    assert said[0] == "got" and score[0] > 0 and "und" not in said[:4] and (said[4], score[4]) == ("und", 0)
    assert langid._letters()[0x10400] == 0x10428  # folded to lower case


# ---------------------------------------------------------------- 5


def test_jaccard_components(clashing, rows):
    have = jaccard_join.near_duplicates(clashing)
    assert got(have, "doc_id", "n_shingles", "component_id") == sorted(brute.jaccard([(r[0], r[1]) for r in rows]), key=str)


@pytest.mark.parametrize("percent", [60, 80, 95])
def test_jaccard_near_the_threshold(spark, percent):
    rng = random.Random(percent)
    base = [f"t{i}" for i in range(60)]
    texts = []
    for k in range(120):
        w = list(base) if k % 3 else [f"u{k}_{i}" for i in range(60)]
        for _ in range(rng.randrange(0, 8)):
            w[rng.randrange(60)] = f"n{rng.randrange(10**6)}"
        texts.append((k, " ".join(w[: rng.randrange(20, 61)])))
    df = spark.createDataFrame(texts, "doc_id bigint, text string")
    assert got(jaccard_join.near_duplicates(df, percent=percent), "doc_id", "n_shingles", "component_id") == sorted(brute.jaccard(texts, percent=percent), key=str)


def _links(texts, n=5, percent=80):
    """(id, links to other rows) by comparing all pairs."""
    sets = []
    for d, x in texts:
        w = brute.spaced((x or "").translate(brute.LOW))
        sets.append((d, {tuple(w[j : j + n]) for j in range(max(1, len(w) - n + 1))} if w else set()))
    return sorted(((d, sum(i != j and bool(a & b) and 100 * len(a & b) >= percent * len(a | b) for j, (_, b) in enumerate(sets))) for i, (d, a) in enumerate(sets)), key=str)


def test_jaccard_counts_all_links(docs, rows):
    assert got(jaccard_join.near_duplicates(docs), "doc_id", "n_links") == _links([r[:2] for r in rows])


@pytest.mark.parametrize("tile", [{"tile_rows": 7}, {"tile_items": 300}])
def test_jaccard_counts_links_over_tiles(spark, tile):
    rng = random.Random(3)
    texts = [(k, " ".join(f"n{rng.randrange(10**6)}" if rng.random() < 0.03 else f"t{i}" for i in range(rng.randrange(35, 80)))) for k in range(80)]
    texts += [(80 + k, texts[k][1]) for k in range(9)]
    join = jaccard_join.JaccardJoin(spark.createDataFrame(texts, "doc_id bigint, text string"))
    join.linked_rows = functools.partial(join.linked_rows, **tile)
    have = [(r["id"], r["n_links"]) for r in join.run().collect()]
    assert sorted(have, key=str) == _links(texts) and max(x for _, x in have) > 10


def test_jaccard_chance_makes_no_neighbourhood(spark, monkeypatch):
    """Texts that share a few words each with the next one are paired; they don't become one neighbourhood of all."""
    joined = []
    monkeypatch.setattr(jaccard_join, "components", lambda links: joined.append(links.count()) or components.components(links))
    rng = random.Random(7)
    shared = [" ".join(f"s{k}_{i}" for i in range(6)) for k in range(61)]
    own = lambda n: " ".join(f"w{rng.randrange(10**9)}" for _ in range(n))
    texts = [(k, f"{shared[k]} {own(50)} {shared[k + 1]}") for k in range(60)]
    assert got(jaccard_join.near_duplicates(spark.createDataFrame(texts, "doc_id bigint, text string")), "doc_id", "n_shingles", "component_id") == sorted(brute.jaccard(texts), key=str)
    assert joined == [0, 0, 0]


@pytest.mark.parametrize("most", [1, 3, 1000])
def test_jaccard_by_pairs_and_by_neighbourhoods(spark, monkeypatch, most):
    """However many classes share an element, no link is lost; without pivots all links come from elements."""
    rng = random.Random(most)
    texts = [(k, " ".join(f"n{rng.randrange(10**6)}" if rng.random() < 0.03 else f"t{i}" for i in range(rng.randrange(35, 80)))) for k in range(80)]
    join = jaccard_join.JaccardJoin(spark.createDataFrame(texts, "doc_id bigint, text string"))
    join.neighbourhoods = functools.partial(join.neighbourhoods, pair_rows=most)
    monkeypatch.setattr(join, "pivots", lambda classes: classes.select(F.col("id").alias("a"), F.col("id").alias("b")).limit(0))
    have = [(r["id"], r["n_shingles"], r["component_id"]) for r in join.run(links=False).collect()]
    assert sorted(have, key=str) == sorted(brute.jaccard(texts), key=str)


def test_signatures_bound_from_above():
    rng = np.random.default_rng(4)
    for n in (1, 5, 70, 400):
        a, b = (np.unique(np.concatenate([rng.integers(0, 2**63, n // 2 + 1, dtype=np.uint64), np.arange(n, dtype=np.uint64) * np.uint64(2**40)])) for _ in range(2))
        apart = len(np.setxor1d(a, b))
        assert jaccard_join.differing(jaccard_join.signature(a), jaccard_join.signature(b)) <= apart
        assert jaccard_join.shared_elements(np.sort(a), np.sort(b)) == len(np.intersect1d(a, b))
        assert jaccard_join.differing(jaccard_join.signature(a), jaccard_join.signature(a[: len(a) // 3 + 1])) <= len(a) - len(a) // 3 - 1


def test_jaccard_slices_large_classes(spark):
    texts = [(k, "one text of some words that very many rows have") for k in range(50)] + [(60 + k, f"other words {k} by which no two rows are alike") for k in range(9)] + [(99, None)]
    join = jaccard_join.JaccardJoin(spark.createDataFrame(texts, "doc_id bigint, text string"))
    join.large = functools.partial(join.large, rows=7)
    assert sorted((r["id"], r["n_shingles"], r["component_id"]) for r in join.run().collect()) == brute.jaccard(texts)
    assert [r["slices"] for r in join.large(join.classes()).collect()] == [8] and join.large(join.classes(), rows=7, most=1).count() == 0


def test_jaccard_edges(spark, nothing, docs, rows):
    assert jaccard_join.near_duplicates(nothing).count() == 0
    kept = {r["doc_id"] for r in jaccard_join.keep_first(docs).collect()}
    assert kept == {d for d, _, c in brute.jaccard([(r[0], r[1]) for r in rows]) if c == d}
    df = spark.createDataFrame([(5, "a b"), (5, "a b"), (6, "A B"), (None, "a b"), (7, None), (8, None)], "doc_id bigint, text string")
    assert got(jaccard_join.near_duplicates(df), "doc_id", "component_id") == sorted([(5, 5), (5, 5), (6, 5), (None, 5), (7, 7), (8, 8)], key=str)


def test_components(spark):
    rng = random.Random(0)
    links = list(zip(p := rng.sample(range(200), 150), p[1:]))[::2] + [(p[0], p[40]), (3, 3)]
    parent = {}

    def root(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        if a != b:
            x, y = root(a), root(b)
            parent[max(x, y)] = min(x, y)
    assert got(components.components(spark.createDataFrame(links, "a bigint, b bigint")), "id", "label") == sorted(((x, root(x)) for x in parent), key=str)


# ---------------------------------------------------------------- 6


@pytest.mark.parametrize("order, split", [(1, 1 << 20), (2, 1 << 20), (2, 3), (3, 2), (4, 1 << 20)])
def test_katz_scores(clashing, rows, monkeypatch, order, split):
    monkeypatch.setattr(katz, "SPLIT", split)
    want, prob, words = brute.katz([(r[0], r[1]) for r in rows], lambda d: brute.fold(d, 7) != 2, order)
    check_katz(katz.score(clashing, langid.fold("doc_id", 7) != 2, order=order), want)
    for a in [0, *list(words)[:10]]:
        for context in [(), (a,), (0, a), (a, a), tuple(list(words)[:2]), tuple(list(words)[:3])]:
            if len(context) < order:
                assert math.isclose(sum(prob(context, w) for w in words) + prob(context, "never seen"), 1, rel_tol=1e-9)


def check_katz(have, want):
    have = {r["doc_id"]: tuple(r) for r in have.collect()}
    assert len(have) == len(want)
    for w in want:
        h = have[w[0]]
        assert h[:5] == w[:5] and all(math.isclose(x, y, rel_tol=1e-9) for x, y in zip(h[5:], w[5:]))


def test_katz_model_scores_other_documents(spark, docs, rows, tmp_path, monkeypatch):
    monkeypatch.setattr(katz, "SPLIT", 5)
    train = [(r[0], r[1]) for r in rows if brute.fold(r[0], 7) != 2]
    model = katz.learn(docs.where(langid.fold("doc_id", 7) != 2), order=3)
    model.save(str(tmp_path / "model"))
    held = katz.Model.load(spark, str(tmp_path / "model"))
    want, prob, words = brute.katz([*[(None, x) for _, x in train], *[r[:2] for r in rows]], lambda d: d is None, 3)
    for m in (model, held):
        check_katz(m.score(docs), want[len(train) :])
        assert m.score(docs.limit(0)).count() == 0
    total = sum(words.values())
    at = {r["word"]: r for r in held.words().collect()}
    assert sum(r["count"] for r in at.values()) == total and sorted(r["count"] for r in at.values()) == sorted(words.values())
    grams, contexts = held.grams(2).collect(), {r["context"]: r for r in held.contexts(2).collect()}
    assert sum(r["count"] for r in grams) == total == sum(c["total"] for c in contexts.values())
    by, share, below = held.learnt.by(1), {}, {r["number"]: r["prob"] for r in at.values()}
    for g in grams:
        c = contexts[g["context"]]
        seen, covered = share.get(g["context"], (0.0, 0.0))
        share[g["context"]] = (seen + c["scale"] * (by[g["count"]] if g["count"] <= 5 else 1) * g["count"] / c["total"], covered + below[g["word"]])
    assert all(math.isclose(seen + contexts[c]["backoff"] * (1 - covered), 1, rel_tol=1e-9) for c, (seen, covered) in share.items())


def test_katz_edges(spark, nothing):
    assert katz.score(nothing, F.lit(True)).count() == 0
    df = spark.createDataFrame([(1, "a b"), (2, None), (2, None)], "doc_id bigint, text string")
    none = {tuple(r) for r in katz.score(df, F.lit(False)).collect()}
    assert {r[:5] for r in none} == {(1, True, 3, 0, 0), (2, True, 1, 0, 0)} and all(r[5] == 0 == r[6] for r in none)
    assert all(math.isfinite(r["score"]) for r in katz.score(df, F.lit(None).cast("boolean")).collect())


def test_katz_leaves_no_questions_on_disk(spark, docs):
    """Shuffle files of the questions go when the answers are written, not when the driver's heap is full."""
    blocks = lambda: {b for b in (x.toString() for x in _java_list(spark)) if b.startswith("shuffle_")}
    before = blocks()
    scored = katz.score(docs, F.col("doc_id") % 2 == 0, order=2)
    for _ in range(100):
        if not (left := blocks() - before):
            break
        time.sleep(0.1)
    assert not left and scored.count() == docs.count()


def test_katz_cuts_texts_once(spark, docs):
    """No step after the first gets a text to cut again, and only ``learn`` writes what the parts have learnt."""
    with storage.recorded() as tables:
        katz.score(docs, F.col("doc_id") % 2 == 0, order=2).count()
    held = [spark.table(name) for _, name, _ in tables]
    packed = [t for t in held if "rows" in t.columns]
    assert len(packed) == 1 and len(held) == 3
    assert all(katz.from_ipc(bytes(r["rows"])).column_names == ["id", "train"] for r in packed[0].select("rows").collect())
    assert [t.where(F.col("block") == katz.LEARNT).count() for t in held if "body" in t.columns] == [0, 0]
    with storage.recorded() as tables:
        katz.learn(docs, order=2)
    assert all(spark.table(name).where(F.col("block") == katz.LEARNT).count() for _, name, _ in tables[1:])


@pytest.mark.parametrize("top, alike", [(50, False), (1 << 40, False), ((1 << 64) - 1, False), ((1 << 64) - 1, True)])
def test_numbers_grouped_with_their_places(top, alike):
    """With room for both in 64 bits, without, and where numbers differ only in the bits that are left out."""
    rng = np.random.default_rng(3)
    for n in (0, 1, 2, 5000):
        some = rng.integers(0, top, max(n // 3, 1), dtype=np.uint64, endpoint=True)
        values = rng.choice(some // np.uint64(8) * np.uint64(8), n) + rng.integers(0, 3, n, dtype=np.uint64) if alike else rng.choice(some, n)
        kinds, which = np.unique(values, return_inverse=True)
        have, one, each = katz.grouped(values, top)
        assert (have == kinds).all() and (each == which).all() and (values[one] == kinds).all() and (np.diff(katz.rising(values, top)[0][np.sort(each) == 0]) > 0).all()


def test_katz_part_answers_what_it_learns_from():
    """The answers that come of the sort are those of a search in the part, of n-grams in training or not."""
    rng = np.random.default_rng(5)
    rows = []
    for n in (0, 1, 40, 300):
        size = rng.integers(0, 6, n)
        contexts = np.sort(rng.choice(np.arange(1, 400, dtype=np.uint64), n, replace=False)) * np.uint64(1 << 50)
        words = [np.sort(rng.choice(np.arange(1, 9, dtype=np.uint64), k, replace=False)) for k in size]
        word = np.concatenate([np.empty(0, np.uint64), *words])
        rows.append([blocks.pack_keys(contexts), *map(blocks.pack_counts, (size, word, word * np.uint64(3), rng.integers(0, 3, len(word))))])
    for scale in (1, 1 << 58):  # with numbers so large that they are ranked first
        asked = [[r[0], r[1], blocks.pack_counts(blocks.unpack_counts(r[2]).astype(np.uint64) * np.uint64(scale)), *r[3:]] for r in rows]
        part, answers = katz.GramPart.learn(asked, blocks.unpack_counts, lambda x: x / 100)
        assert answers == [part.answer(r) for r in asked] == [katz.GramPart.unpack(part.pack()).answer(r) for r in asked]
        assert part.count.sum() == sum(int(blocks.unpack_counts(r[4]).sum()) for r in rows)


def test_counts_packed():
    for top in (0, 255, 256, 65535, 1 << 16, 1 << 32, (1 << 63) + 5):
        values = np.array([0, 1, top], dtype=np.uint64)
        assert (blocks.unpack_counts(blocks.pack_counts(values)) == values).all()
    assert len(blocks.unpack_counts(blocks.pack_counts(np.empty(0, dtype=np.int64)))) == 0


def _java_list(spark):
    held = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllBlocks()
    return [held.apply(i) for i in range(held.size())]


def test_discounts():
    for n in ([0, 100, 40, 20, 12, 8, 6], [0, 3, 9, 1, 7, 2, 5], [0, 0, 0, 0, 0, 0, 0], [0, 5, 0, 1, 0, 0, 0]):
        d = katz.discounts(np.array(n))
        assert ((d[1:] > 0) & (d[1:] <= 1)).all() and np.allclose(d, brute.discounts(dict(enumerate(n))))


# ---------------------------------------------------------------- 7


@pytest.mark.parametrize("limits", [(substring_dedup.SHARD_WORDS, substring_dedup.HOT_BITS), (150, 1)])
def test_repeats(clashing, rows, monkeypatch, limits):
    monkeypatch.setattr(substring_dedup, "SHARD_WORDS", limits[0])
    monkeypatch.setattr(substring_dedup, "HOT_BITS", limits[1])
    have = substring_dedup.remove_repeats(clashing)
    assert got(have, "doc_id", "n_words", "n_removed", "kept") == sorted(brute.repeats([(r[0], r[1]) for r in rows]), key=str)
    assert set(clashing.columns) <= set(have.columns)
    cut = substring_dedup.cut_repeats(clashing, size_col="n_chars")
    texts = {r[0]: r[3] if r[2] else None for r in brute.repeats([(r[0], r[1]) for r in rows])}
    assert cut.columns == clashing.columns and cut.where("kept <> 'kept' or _id <> '_id' or row <> 'row'").count() == 0
    for r, (_, x, *_) in zip(sorted(cut.select("doc_id", "text", "n_chars").collect()), sorted(rows)):
        want = x if texts[r["doc_id"]] is None else texts[r["doc_id"]]
        assert (r["text"], r["n_chars"]) == (want, len(want or ""))
    assert all(sum(s["end"] - s["start"] for s in r["removed"]) == r["n_removed"] for r in have.collect())


def test_short_windows(spark):
    rng = random.Random(6)
    texts = [(i, " ".join(rng.choice("abc") for _ in range(rng.randrange(0, 60)))) for i in range(40)]
    df = spark.createDataFrame(texts, "doc_id bigint, text string")
    assert got(substring_dedup.remove_repeats(df, window=8, anchor=3), "doc_id", "n_words", "n_removed", "kept") == sorted(brute.repeats(texts, 8), key=str)


def test_repeats_edges(spark, nothing):
    assert substring_dedup.remove_repeats(nothing).count() == 0
    long = " ".join(map(str, range(70)))
    df = spark.createDataFrame([(4, long), (4, long), (None, long), (9, long)], "doc_id bigint, text string")
    assert got(substring_dedup.remove_repeats(df), "doc_id", "n_removed") == sorted([(4, 0), (4, 0), (None, 70), (9, 70)], key=str)


def test_answers_are_one_file_a_bucket(spark, docs, monkeypatch):
    """Each part answers all blocks, so that undealt there are files by the square of the parts."""
    monkeypatch.setattr(substring_dedup, "BLOCK_BYTES", 1 << 10)
    coalesce = "spark.sql.adaptive.coalescePartitions.enabled"
    spark.conf.set(coalesce, "false")
    try:
        with storage.recorded() as tables:
            found = substring_dedup.remove_repeats(docs)
        packed, answers = (spark.table(name) for _, name, _ in tables)
        asking = packed.select("block", F.posexplode("asked").alias("part", "body")).where(F.length("body") > 0)
        assert packed.count() > 4 and sorted(answers.select("block", "part").collect()) == sorted(asking.select("block", "part").collect())
        assert len(answers.inputFiles()) <= 4
        assert found.count() == docs.count()
    finally:
        spark.conf.unset(coalesce)


def test_fm_index():
    rng = random.Random(8)
    text = np.array([rng.randrange(0, 5) for _ in range(700)])
    for k in (2, 3, 7, 12):
        index = fm_index.FMIndex(text, k)
        query = np.array([rng.randrange(1, 6) for _ in range(400)] + text[100:130].tolist())
        found = index.windows(query, np.array([0, 150, 150, len(query)])) >= 0
        have = {tuple(text[i : i + k]) for i in range(len(text) - k + 1)}
        for i in range(len(query)):
            inside = i + k <= 150 or i >= 150 and i + k <= len(query)
            assert found[i] == (inside and 0 not in query[i : i + k] and tuple(query[i : i + k]) in have), (k, i)
    marks = np.array([rng.randrange(10**6) for _ in text])
    index = fm_index.FMIndex(text, 3, marks)
    by = {}
    for i in range(len(text) - 2):
        by.setdefault(tuple(text[i : i + 3]), []).append(marks[i])
    found = index.windows(text, np.array([0, len(text)]))
    assert all(index.least[r] == min(by[tuple(text[i : i + 3])]) for i, r in enumerate(found) if r >= 0) and (found >= 0).sum() > 200
    held = sum(b.words.nbytes + b.near.nbytes + b.far.nbytes for b in [*fm_index.FMIndex(np.arange(1, 200_001), 50).wavelet.levels])
    assert held < 200_000 * 18 * 1.3 / 8
    x = np.array([rng.randrange(0, 9) for _ in range(300)])
    matrix = fm_index.WaveletMatrix(x)
    at, symbol = np.array([rng.randrange(0, 301) for _ in range(200)]), np.array([rng.randrange(0, 9) for _ in range(200)])
    assert matrix.rank(symbol, at).tolist() == [int((x[:a] == s).sum()) for a, s in zip(at, symbol)]


def test_sliding_argmin():
    x = np.random.default_rng(1).integers(0, 9, 200).astype(np.uint64)
    for span in (1, 2, 5, 35):
        assert substring_dedup.sliding_argmin(x, span).tolist() == [i + int(x[i : i + span].argmin()) for i in range(len(x) - span + 1)]


# ---------------------------------------------------------------- 8


def test_token_files(spark, clashing, rows):
    path = PATHS[catalog.WORD_BPE]
    ids, _ = brute.tokenized(path, [r[1] for r in rows])
    folder = token_files.new_folder(spark)
    token_files.write_tokens(bpe.encode_in_place(clashing, path, last=1, narrow=True), folder, token_files.range_bounds(clashing, "doc_id", 4))
    start, want = 0, []
    for d, i in sorted((r[0], [*i, 1]) for r, i in zip(rows, ids)):
        want.append((d, start, len(i), zlib.crc32(np.array(i, dtype="<u4").tobytes())))
        start += len(i)
    assert got(token_files.token_offsets(spark, folder, narrow=True), "doc_id", "start", "n_tokens", "ids_crc32") == sorted(want, key=str)
    one = token_files.read_tokens(spark, folder, [rows[5][0]], narrow=True)
    assert one.first()["ids"] == [*ids[5], 1]
    assert one.count() == 1 and "PushedFilters: [In(doc_id" in one._jdf.queryExecution().executedPlan().toString() or "EqualTo(doc_id" in one._jdf.queryExecution().executedPlan().toString()


def test_token_file_edges(spark):
    with pytest.raises(ValueError, match="16 bits"):
        bpe.encode_in_place(spark.range(1).selectExpr("id AS doc_id", "'a' AS text"), PATHS[catalog.WORD_BPE], last=1 << 16, narrow=True)
    df = spark.createDataFrame([(3, [1, 2]), (3, [1, 2]), (None, [5]), (1, None), (2, [])], "doc_id bigint, ids array<int>")
    folder = token_files.new_folder(spark)
    token_files.write_tokens(df, folder, token_files.range_bounds(df, "doc_id", 3))
    assert got(token_files.token_offsets(spark, folder), "doc_id", "start", "n_tokens") == sorted([(None, 0, 1), (1, 1, 0), (2, 1, 0), (3, 1, 2), (3, 3, 2)], key=str)
    empty = token_files.new_folder(spark)
    token_files.write_tokens(df.limit(0), empty, [])
    assert token_files.token_offsets(spark, empty).count() == 0


# ---------------------------------------------------------------- 9


def test_warc_audit(spark, tmp_path):
    rows = [(i, f"http://x/{i}", None if i == 3 else "a\r\n\r\nb" * i + "é") for i in range(40)] + [(None, None, "last"), (7, "http://x/7", "again")]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string").withColumn("file", F.lit(1))
    for files in (1, 3):
        folder = warc.new_folder(spark)
        warc.write_warc(pages, folder, files, replicas=2, spoilt=F.col("page_id").isin(5, 21))
        records, bad = warc.audit(spark, f"{folder}/replica=0", f"{folder}/replica=1", fanout=3)
        assert records.count() == len(rows)
        spoilt = {r["record_id"] for r in records.join(bad, ["file", "idx"], "left_semi").collect()}
        assert spoilt == {"<urn:page:5>", "<urn:page:21>"} and {r["status"] for r in bad.collect()} == {"changed"}
        _, same = warc.audit(spark, f"{folder}/replica=0", f"{folder}/replica=0")
        assert same.count() == 0
    raw = warc.leaves(spark, f"{folder}/replica=0").where("record_id = '<urn:page:2>'").first()
    text = b"WARC/1.0\r\nWARC-Type: resource\r\nWARC-Record-ID: <urn:page:2>\r\nWARC-Target-URI: http://x/2\r\nContent-Type: text/html\r\nContent-Length: 14\r\n\r\na\r\n\r\nba\r\n\r\nb\xc3\xa9\r\n\r\n"
    assert raw["sha256"] == hashlib.sha256(text).hexdigest() and raw["stop"] - raw["start"] == len(text)


def test_warc_missing_records(spark):
    leaf = spark.createDataFrame([(0, i, 10 * i, 10 * i + 10, f"{i}") for i in range(20)], "file int, idx bigint, start bigint, stop bigint, sha256 string")
    a, b = warc.tree(leaf, 4), warc.tree(leaf.where("idx < 18"), 4)
    assert got(warc.differing(a, b, 4), "idx", "status") == [(18, "missing"), (19, "missing")]
    assert got(warc.differing(b, a, 4), "idx", "status") == [(18, "added"), (19, "added")]
    assert warc.differing(warc.tree(leaf.limit(0)), warc.tree(leaf.limit(0))).count() == 0


# ---------------------------------------------------------------- 10


def test_fingerprints(spark, clashing, rows):
    have = got(fingerprint.with_next(clashing).mapInArrow(catalog.compared, "doc_id bigint, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"), "doc_id", "n_chars", "edited_sha256")
    held = sorted(((r[0], r[1] or "") for r in rows), reverse=True)
    want = []
    for i, (d, x) in enumerate(held):
        y, k = held[(i + 1) % len(held)][1], len(x) // 2
        want.append((d, len(x), brute.sha(x[: len(x) - k] + y[:k])))
    assert have == sorted(want, key=str)


def test_fingerprints_resist_shifts():
    rng = random.Random(3)
    text = " ".join(f"word{rng.randrange(10**6)}" for _ in range(400))
    a, b, c, d = fingerprint.fingerprints([text.encode(), ("inserted " + text).encode(), text[:2000].encode(), b"something else entirely " * 3])
    assert fingerprint.fingerprints([text.encode()])[0] == a
    assert fingerprint.containment(a, b) > 0.95 and fingerprint.containment(a, c) > 0.9 and fingerprint.containment(a, d) == 0.0
    assert fingerprint.fingerprints([b""]) == [""] and fingerprint.containment("", "") == 1.0 and fingerprint.containment("", a) == 0.0


def test_fingerprint_edges(spark, nothing, docs, rows):
    assert fingerprint.with_next(nothing).count() == 0 == fingerprint.fingerprint(nothing).count()
    by = {}
    for r in fingerprint.fingerprint(docs).collect():
        by[r["doc_id"]] = r["fingerprint"]
    for a in rows:
        for b in rows[:10]:
            if (a[1] or "") == (b[1] or ""):
                assert by[a[0]] == by[b[0]]
    one = spark.createDataFrame([(1, "lonely text")], "doc_id bigint, text string")
    assert [len(x) for x in fingerprint.pairs_with_next(iter(fingerprint.with_next(one).toArrow().to_batches()))] == [1]
    ties = spark.createDataFrame([(1, "a"), (1, "b"), (None, "c"), (None, None)], "doc_id bigint, text string")
    assert fingerprint.with_next(ties).where("not ghost").count() == 4


# ---------------------------------------------------------------- shared parts


def test_word_hashes_follow_words():
    import pyarrow as pa

    rng = random.Random(9)
    texts = [" ".join(rng.choice(["ab", "ba", "abc", "Ab", "é", "x" * 300]) for _ in range(rng.randrange(0, 40))) for _ in range(60)] + ["", None, "\t \n"]
    words = textarrays.Words(*textarrays.texts_of(pa.array(texts)), textarrays.NON_SPACE)
    flat = [w.encode() for t in texts for w in brute.spaced(t)]
    assert [words.word(i) for i in range(len(words))] == flat
    by = {}
    for w, h in zip(flat, words.hashes().tolist()):
        assert by.setdefault(w, h) == h
    assert len(set(by.values())) == len(by)
    for i, t in enumerate(texts):
        assert words.joined(words.first[i], words.first[i + 1]).decode() == " ".join(brute.spaced(t))


def test_tables_are_released(spark):
    with storage.recorded() as tables:
        df = storage.stored(spark.range(5), "id", 2)
    assert df.count() == 5
    storage.release(tables)
    with pytest.raises(Exception):
        spark.table(tables[0][1]).count()
