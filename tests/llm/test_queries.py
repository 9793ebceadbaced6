"""The registered queries and the pipeline, on the smallest tables and on planted documents."""

import zlib

import duckdb
import pytest

import corpus_pipeline
from codist.llm import catalog, fingerprint, langid

from . import brute

public_tokenizers = pytest.importorskip("public_tokenizers")


@pytest.fixture(scope="module")
def texts(sf):
    return duckdb.sql(f"SELECT doc_id, text FROM '{sf}/documents.parquet' ORDER BY doc_id").fetchall()


def rows_of(spark, sf, name, *columns):
    return sorted(tuple(r) for r in catalog.QUERIES[name](spark, sf).select(*columns).collect())


@pytest.mark.parametrize("name", sorted(catalog.ORACLES))
def test_sql_twins(spark, sf, name):
    con = duckdb.connect()
    for t in ("conversations", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    held = con.execute(catalog.ORACLES[name])
    columns = [d[0] for d in held.description]
    assert rows_of(spark, sf, name, *columns) == sorted(held.fetchall())


def test_op1(spark, sf, texts):
    ids, back = brute.tokenized(public_tokenizers.path(catalog.BYTE_BPE), [x for _, x in texts])
    want = [(d, len(i), brute.sha(",".join(map(str, i))), brute.sha(t)) for (d, _), i, t in zip(texts, ids, back)]
    assert rows_of(spark, sf, "op1_bpe", "doc_id", "n_tokens", "ids_sha256", "decoded_sha256") == want


def test_op3(spark, sf, texts):
    items = duckdb.sql(f"SELECT item_id, text FROM '{sf}/benchmark.parquet'").fetchall()
    want = [(d, n, h, len(s), brute.sha(",".join(s)), h > 0) for d, n, h, s in brute.contamination(texts, items)]
    assert rows_of(spark, sf, "op3_decontaminate", "doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated") == want


def test_op4(spark, sf, texts):
    """Every row against plain Kneser-Ney models of the same sample."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    langs = dict(duckdb.sql(f"SELECT doc_id, lang FROM '{sf}/documents.parquet'").fetchall())
    learned, _ = langid.sampled(docs.where(langid.fold("doc_id", 4) != 2), "doc_id", "text", "lang", 400)
    bits = brute.kneser_ney(learned)
    have = rows_of(spark, sf, "op4_language", "doc_id", "held_out", "lang_pred", "score", "cross_entropy")
    assert [r[:2] for r in have] == [(d, brute.fold(d, 4) == 2) for d, _ in texts]
    for (_, text), (_, _, said, score, least) in zip(texts, have):
        want = bits(text)
        assert 0 <= score <= 1 and least == pytest.approx(min(want.values()), abs=1e-4) and want[said] == pytest.approx(least, abs=1e-4)
    out = [r for r in have if r[1]]
    assert sum(r[2] == langs[r[0]] for r in out) >= 0.95 * len(out)


def test_op5(spark, sf, texts):
    assert rows_of(spark, sf, "op5_jaccard", "doc_id", "n_shingles", "component_id") == brute.jaccard(texts)


def test_op6(spark, sf, texts):
    want, _, _ = brute.katz(texts, lambda d: brute.fold(d, 7) != 2)
    have = rows_of(spark, sf, "op6_katz", "doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score")
    assert [h[:5] for h in have] == [w[:5] for w in want]
    assert all(x == pytest.approx(y, rel=1e-9) for h, w in zip(have, want) for x, y in zip(h[5:], w[5:]))
    per = lambda k: sum(h[k] for h in have if h[1]) / sum(h[2] for h in have if h[1])
    assert per(6) > per(5)  # held-out text is likelier under the model than under the base


def test_op7(spark, sf, texts):
    want = [(d, n, k, brute.sha(t)) for d, n, k, t in brute.repeats(texts)]
    assert rows_of(spark, sf, "op7_substrings", "doc_id", "n_words", "n_removed", "kept_sha256") == want


def test_op8(spark, sf, texts):
    ids, _ = brute.tokenized(public_tokenizers.path(catalog.WORD_BPE), [x for _, x in texts])
    start, want = 0, []
    for (d, _), i in zip(texts, ids):
        raw = b"".join(k.to_bytes(4, "little") for k in [*i, 1])
        want.append((d, start, len(i) + 1, zlib.crc32(raw)))
        start += len(i) + 1
    assert rows_of(spark, sf, "op8_token_files", "doc_id", "start", "n_tokens", "ids_crc32") == want


def test_op10(spark, sf, texts):
    have = rows_of(spark, sf, "op10_fingerprint", "doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next")
    want = brute.fingerprinted(texts, fingerprint._GEAR)
    assert [h[:5] for h in have] == [w[:5] for w in want]
    assert all(h[5:] == pytest.approx(w[5:]) for h, w in zip(have, want))
    near = [r for r in have if r[1] > 400]
    assert sum(r[5] for r in near) / len(near) > 0.4 and sum(r[6] for r in near) / len(near) < 0.1


@pytest.fixture(scope="module")
def planted(spark, docs, rows, tmp_path_factory):
    """A folder with documents and a benchmark that leaks into some of them."""
    where = str(tmp_path_factory.mktemp("planted"))
    item = " ".join(f"leak{i}" for i in range(14))
    extra = [(9001, f"An answer: {item}.", "en", "s", 99), (9002, "нет такого языка совсем " * 9, None, "s", 9)]
    docs.unionByName(spark.createDataFrame(extra, docs.schema)).write.parquet(f"{where}/documents.parquet")
    spark.createDataFrame([(1, item)], "item_id bigint, text string").write.parquet(f"{where}/benchmark.parquet")
    return where, [*rows, *extra], [(1, item)]


def test_pipeline_stages(spark, planted, tmp_path):
    where, rows, items = planted
    docs, columns = spark.read.parquet(f"{where}/documents.parquet"), ["doc_id", "text", "lang", "source", "n_chars"]
    held = {r[0]: r[1] for r in rows}
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, where)
        out.write.parquet(str(tmp_path / str(k)))
        docs = spark.read.parquet(str(tmp_path / str(k)))
        have = {r["doc_id"]: r["text"] for r in docs.collect()}
        pairs = sorted(held.items())
        if k == 0:
            assert set(have) <= set(held) and all(have[d] == held[d] for d in have)
            gone = set(held) - set(have)
            assert 9002 in gone and all(not held[d] or d == 9002 or len(held[d].split()) < 12 or len(set(held[d])) < 8 for d in gone)
            assert docs.where("lang is null").count() == 0
            held = have
        elif k == 1:
            held = {d: held[d] for d, _, c in brute.jaccard(pairs) if c == d}
            assert have == held
        elif k == 2:
            held = {d: t if gone else held[d] for d, _, gone, t in brute.repeats(pairs)}
            assert have == held
        elif k == 3:
            held = {d: held[d] for d, _, hit, _ in brute.contamination(pairs, items) if not hit}
            assert have == held and 9001 not in have
        if k < 4:
            assert docs.columns == columns
    ids, back = brute.tokenized(public_tokenizers.path(catalog.BYTE_BPE), [x for _, x in sorted(held.items())])
    assert [(r["doc_id"], r["n_tokens"], r["ids"], r["text"]) for r in docs.orderBy("doc_id").collect()] == [(d, len(i), i, t) for d, i, t in zip(sorted(held), ids, back)]


def test_pipeline_run(spark, planted):
    where, _, _ = planted
    assert corpus_pipeline.run(spark, where).count() > 0


def test_pipeline_without_documents(spark, planted, tmp_path):
    where, _, _ = planted
    docs = spark.read.parquet(f"{where}/documents.parquet").limit(0)
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, where)
        out.write.parquet(str(tmp_path / str(k)))
        docs = spark.read.schema(out.schema).parquet(str(tmp_path / str(k)))
        assert docs.count() == 0
