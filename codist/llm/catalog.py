"""The queries of this subpackage: each applies one operator to its whole table."""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, chat, decontaminate, fingerprint, jaccard_join, katz, langid, substring_dedup, token_files, warc
from .storage import parallelism

BYTE_BPE, WORD_BPE = "byte_bpe_50k.json", "word_bpe_49k.json"


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def sha256_hex(x: bytes) -> str:
    return hashlib.sha256(x).hexdigest()


def op1_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = tokenizer_path(BYTE_BPE)
    ids = bpe.encode(table(spark, sf_dir, "documents"), path)
    with open(path, encoding="utf-8") as f:
        config = spark.sparkContext.broadcast(f.read())

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The number of ids and the digests of ids and decoded text."""
        for batch in batches:
            for i in range(0, batch.num_rows, 1000):
                part = batch.slice(i, 1000)
                lists = part.column("ids")
                flat, at = lists.values.to_numpy(zero_copy_only=False), lists.offsets.to_numpy().tolist()
                yield pa.RecordBatch.from_arrays([
                    part.column("doc_id"),
                    pa.array([k - j for j, k in zip(at, at[1:])], pa.int64()),
                    pa.array([sha256_hex(",".join(map(str, flat[j:k].tolist())).encode()) for j, k in zip(at, at[1:])]),
                    pa.array([sha256_hex(x.encode()) for x in bpe.decoded(config.value, lists)]),
                ], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return ids.mapInArrow(digest, "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string")


def op2_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    planted = spark.sql(r"""SELECT -7L AS conv_id, t.turn, t.role, r'\### Assistant: </turn> ok' AS text FROM VALUES (0L, 'user'), (1L, 'assistant') AS t(turn, role)""")
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(planted)
    read = chat.read_turns(chat.format_chats(turns.select("conv_id", "turn", "role", chat.text_parts(F.coalesce("text", F.lit(""))).alias("parts"))))
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return read.select(
        "conv_id",
        F.size("turns").cast("bigint").alias("n_turns"),
        F.sha2(said, 256).alias("turns_sha256"),
        F.length("loss_text").cast("bigint").alias("loss_chars"),
        F.sha2("loss_text", 256).alias("loss_sha256"),
        F.length("formatted").cast("bigint").alias("formatted_chars"),
    )


OP2_SQL = r"""
WITH t AS (
  SELECT conv_id, turn, coalesce(role, '') AS r, coalesce(text, '') AS x FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'
), c AS (
  SELECT conv_id, count(*)::BIGINT AS n_turns,
         string_agg(r || chr(10) || x || chr(10), '' ORDER BY turn NULLS FIRST, r, x) AS said,
         coalesce(string_agg(x, '' ORDER BY turn NULLS FIRST, r, x) FILTER (r = 'assistant'), '') AS loss,
         sum(length(replace(replace(replace(r, '\', '\-'), '<', '\('), '>', '\)'))
             + length(replace(replace(x, '\', '\-'), '<', '\(')) + 16)::BIGINT AS formatted_chars
  FROM t GROUP BY conv_id
)
SELECT conv_id, n_turns, sha256(said) AS turns_sha256, length(loss)::BIGINT AS loss_chars, sha256(loss) AS loss_sha256, formatted_chars FROM c
"""


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.find_contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    hit = decontaminate.hit_words()
    return found.select(
        "doc_id",
        "n_words",
        hit.alias("n_hit"),
        F.size("items").cast("bigint").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        (hit > 0).alias("contaminated"),
    )


def compared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of each document and the next: the fingerprints of its text, of its edited text, and the next one's."""
    for rows in fingerprint.pairs_with_next(batches):
        edited = [x[: len(x) - len(x) // 2] + y[: len(x) // 2] for _, x, y in rows]
        own = fingerprint.fingerprints([x.encode() for _, x, _ in rows])
        after = [*own[1:], None]
        for i, (_, _, y) in enumerate(rows):
            if after[i] is None or rows[i + 1][1] != y:
                (after[i],) = fingerprint.fingerprints([y.encode()])
        changed = fingerprint.fingerprints([x.encode() for x in edited])
        yield pa.RecordBatch.from_pydict({
            "doc_id": pa.array([x[0] for x in rows], pa.int64()),
            "n_chars": pa.array([len(x[1]) for x in rows], pa.int64()),
            "edited_sha256": [sha256_hex(x.encode()) for x in edited],
            "fingerprint": own,
            "edited_fingerprint": changed,
            "near_edited": pa.array(map(fingerprint.containment, own, changed), pa.float64()),
            "near_next": pa.array(map(fingerprint.containment, own, after), pa.float64()),
        })


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    side = langid.fold("doc_id", 4)
    models = langid.learn_models(docs.where(side != 2))
    return langid.identify(docs.select("doc_id", "text"), models).select("doc_id", (side == 2).alias("held_out"), "lang_pred", "score", "cross_entropy", "accepted")


def op5_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.near_duplicates(table(spark, sf_dir, "documents"))


def op6_katz(spark: SparkSession, sf_dir: str) -> DataFrame:
    return katz.score(table(spark, sf_dir, "documents"), langid.fold("doc_id", 7) != 2, order=2)


def op7_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return substring_dedup.remove_repeats(docs).select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def op8_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    ids = bpe.encode_in_place(docs, tokenizer_path(WORD_BPE), last=1, narrow=True)
    path = token_files.new_folder(spark)
    token_files.write_tokens(ids, path, token_files.range_bounds(docs, "doc_id", parallelism(spark)))
    return token_files.token_offsets(spark, path, narrow=True)


WARC_FILE_BYTES = 16 << 20


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Writes all pages as two replicas of WARC files, the second with a changed byte in every 97th record, and audits them."""
    pages = table(spark, sf_dir, "pages").select("page_id", "url", "html")
    files = warc.n_files(pages, "html", WARC_FILE_BYTES)
    spoilt = (F.pmod("page_id", F.lit(97)) == 5) & (F.length("html") > 0)
    folder = warc.new_folder(spark)
    warc.write_warc(pages, folder, files, replicas=2, spoilt=spoilt)
    one, two = f"{folder}/replica=0", f"{folder}/replica=1"
    records, bad = warc.audit(spark, one, two)
    page = F.regexp_extract("record_id", "(-?[0-9]+)>$", 1).cast("bigint")
    return records.join(bad.select("file", "idx", "status"), ["file", "idx"], "left").select(page.alias("page_id"), F.col("file").cast("bigint").alias("file"), F.col("start").alias("offset"), (F.col("stop") - F.col("start")).alias("length"), F.col("sha256").alias("record_sha256"), F.coalesce("status", F.lit("intact")).alias("status"))


OP9_SQL = r"""
WITH f AS (SELECT greatest(1, -((-sum(octet_length(encode(coalesce(html, ''))))) // 16777216))::BIGINT AS files FROM pages),
r AS (
  SELECT page_id, page_id % files AS file, coalesce(html, '') AS html,
         'WARC/1.0' || chr(13) || chr(10) || 'WARC-Type: resource' || chr(13) || chr(10) || 'WARC-Record-ID: <urn:page:' || page_id || '>' || chr(13) || chr(10)
         || 'WARC-Target-URI: ' || coalesce(url, '') || chr(13) || chr(10) || 'Content-Type: text/html' || chr(13) || chr(10) || 'Content-Length: '
         || octet_length(encode(coalesce(html, ''))) || chr(13) || chr(10) || chr(13) || chr(10) || coalesce(html, '') || chr(13) || chr(10) || chr(13) || chr(10) AS rec
  FROM pages, f
)
SELECT page_id, file::BIGINT AS file,
       (sum(octet_length(encode(rec))) OVER (PARTITION BY file ORDER BY page_id) - octet_length(encode(rec)))::BIGINT AS "offset",
       octet_length(encode(rec))::BIGINT AS length, sha256(rec) AS record_sha256,
       CASE WHEN page_id % 97 = 5 AND html <> '' AND substr(html, 1, 1) <> '#' THEN 'changed' ELSE 'intact' END AS status
FROM r
"""


def op10_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    fingerprint.ship(spark)
    rows = fingerprint.with_next(table(spark, sf_dir, "documents"))
    return rows.mapInArrow(compared, "doc_id bigint, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_bpe, op2_chat, op3_decontaminate, op4_language, op5_jaccard, op6_katz, op7_substrings, op8_token_files, op9_warc, op10_fingerprint)}

ORACLES: dict[str, str] = {"op2_chat": OP2_SQL, "op9_warc": OP9_SQL}
