"""The queries opN_* over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, exact, fingerprints, html, katz, licences, mixing, near, quality, warc
from .common import scratch


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


#: Production parameters of the mixture: sources of 90 percent of the largest entropy at least, as many tokens as there are.
MIXTURE = {"entropy": 0.9, "budget_share": 1.0, "seed": 7}


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = exact.exact_duplicates(table(spark, sf_dir, "documents"), every_digest=True)
    return found.select("doc_id", "keep_id", "group_size", "kept", F.col("digest").alias("text_sha256"))


def op2_document_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.edited(table(spark, sf_dir, "documents")).withColumn("fingerprint", F.lower(F.hex("fingerprint"))).withColumn("edited_fingerprint", F.lower(F.hex("edited_fingerprint")))


def op3_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_sources(table(spark, sf_dir, "documents"), **MIXTURE).withColumn("weight", F.round("weight", 9))


def op4_licence_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = licences.scan(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "canonical_sha256", "licence", F.concat_ws(",", "notices").alias("notices"))


def op5_warc_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch(spark, "warc")
    warc.archive(table(spark, sf_dir, "pages"), path)
    back = warc.read_archive(spark, path)
    return back.select("page_id", F.octet_length("payload").cast("long").alias("payload_bytes"), F.sha1("payload").alias("payload_digest"), warc.header_field("WARC-Type").alias("record_type"), F.col("refers_to"))


def op6_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_digests(table(spark, sf_dir, "documents"))


def bpe_digests(docs: DataFrame) -> DataFrame:
    path = tokenizer_path()
    coded = bpe.decode(bpe.encode(docs, path), path)
    return coded.select("doc_id", "n_tokens", F.sha2("token_ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op7_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return katz.score(table(spark, sf_dir, "documents"))


def op8_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near.near_duplicates(table(spark, sf_dir, "documents"))


def op9_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract(table(spark, sf_dir, "pages")).withColumn("n_chars", F.length("text").cast("long"))


def quality_model(docs: DataFrame, labels: DataFrame) -> dict:
    """Trained on labelled rows whose crc32 of the id as text, modulo 5, is not 0."""
    seen = labels.filter(F.crc32(F.col("doc_id").cast("string")) % 5 != 0).select("doc_id", "quality")
    return quality.train(docs, seen)


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = quality.score(docs.select("doc_id", "text"), quality_model(docs, table(spark, sf_dir, "labels")))
    held = F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))) % 5 == 0
    return scored.select("doc_id", held.alias("held_out"), F.col("quality_score").alias("score"), (F.col("quality_score") >= quality.THRESHOLD).cast("int").alias("predicted"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    own = [op1_exact_dedup, op2_document_fingerprints, op3_source_mixing, op4_licence_scan, op5_warc_archive, op6_bpe, op7_language_model, op8_near_duplicates, op9_html_extraction, op10_quality, pipeline]
    return {f.__name__: f for f in own}


_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _canonical_sql(text: str) -> str:
    t = f"lower(coalesce({text}, ''))"
    t = f"regexp_replace({t}, '(^|\\n)[^\\p{{L}}\\p{{N}}\\n]*(copyright|©|\\(c\\))[ \\t]*(\\(c\\)|©|[0-9]{{4}}|by )[^\\n]*', '\\1', 'g')"
    t = f"regexp_replace({t}, '(^|\\n)[^\\p{{L}}\\p{{N}}\\n]*all rights reserved[^\\p{{L}}\\p{{N}}\\n]*', '\\1', 'g')"
    t = f"regexp_replace({t}, '[^\\p{{L}}\\p{{N}}\\n]+', ' ', 'g')"
    t = f"concat(' ', replace(replace({t}, ' ', '  '), chr(10), ' ' || chr(10) || ' '), ' ')"
    for other, spelled in licences.SPELLINGS:
        wide = lambda x: f"' {x.replace(' ', '  ')} '"
        t = f"replace({t}, {wide(other)}, {wide(spelled)})"
    return f"trim(regexp_replace(regexp_replace({t}, ' *\n[ \n]*', chr(10), 'g'), ' +', ' ', 'g'), ' ' || chr(10))"


def _licence_sql() -> str:
    quoted = lambda x: "'" + x.replace("'", "''") + "'"
    known = ", ".join(f"({quoted(n)}, {quoted(t)})" for n, t in licences.NOTICES)
    whole = ", ".join(f"({quoted(name)}, {quoted(digest)})" for name, _, digest in licences.WHOLE)
    return f"""WITH known AS (SELECT digest, min(licence) AS licence FROM (SELECT licence, sha256(replace({_canonical_sql("t")}, chr(10), ' ')) AS digest FROM (VALUES {known}) v(licence, t) UNION ALL SELECT * FROM (VALUES {whole}) w(licence, digest)) f GROUP BY 1),
 doc AS (SELECT doc_id, {_canonical_sql("text")} AS form FROM documents), lines AS (SELECT DISTINCT doc_id, licence FROM (SELECT doc_id, unnest(string_split(form, chr(10))) AS line FROM doc) l JOIN known ON digest = sha256(line))
 SELECT doc_id, sha256(replace(form, chr(10), ' ')) AS canonical_sha256, known.licence, coalesce((SELECT string_agg(lines.licence, ',' ORDER BY lines.licence) FROM lines WHERE lines.doc_id = doc.doc_id), '') AS notices
 FROM doc LEFT JOIN known ON digest = sha256(replace(form, chr(10), ' '))"""


def _mixing_sql() -> str:
    """The same grid search, written out round by round, and the same keyed orders."""
    grid, rounds, goal = mixing.GRID, mixing.ROUNDS, MIXTURE["entropy"]
    parts = [
        "sized AS (SELECT doc_id, coalesce(source, '') AS source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS tokens, md5('%d:' || doc_id) AS h FROM documents)" % MIXTURE["seed"],
        "totals AS (SELECT source, CAST(sum(tokens) AS BIGINT) AS source_tokens FROM sized GROUP BY source)",
        "share AS (SELECT source_tokens / (SELECT CAST(sum(source_tokens) AS DOUBLE) FROM totals) AS p FROM totals WHERE source_tokens > 0)",
        "r0 AS (SELECT CAST(0.0 AS DOUBLE) AS low, CAST(1.0 AS DOUBLE) AS high)",
    ]
    for k in range(rounds):
        parts.append(f"g{k} AS (SELECT low, high, i, low + (high - low) * i / {grid} AS a FROM r{k}, (SELECT unnest(generate_series(0, {grid})) AS i) s)")
        parts.append(f"h{k} AS (SELECT any_value(low) AS low, any_value(high) AS high, i, a, ln(sum(pow(p, a))) - sum(pow(p, a) * ln(pow(p, a))) / sum(pow(p, a)) AS h FROM g{k}, share GROUP BY i, a)")
        parts.append(f"b{k} AS (SELECT low, high, coalesce((SELECT max(i) FROM h{k} WHERE h >= {goal} * (SELECT ln(count(*)) FROM share) - 1e-12), 0) AS i FROM r{k})")
        parts.append(f"r{k + 1} AS (SELECT low + (high - low) * i / {grid} AS low, low + (high - low) * least(i + 1, {grid}) / {grid} AS high FROM b{k})")
    parts += [
        f"final AS (SELECT low AS a FROM r{rounds})",
        "norm AS (SELECT sum(pow(p, a)) AS s FROM share, final)",
        f"weighed AS (SELECT source, source_tokens, CASE WHEN source_tokens > 0 THEN pow(source_tokens / (SELECT CAST(sum(source_tokens) AS DOUBLE) FROM totals), (SELECT a FROM final)) / (SELECT s FROM norm) ELSE 0 END AS weight, source_tokens // {mixing.BLOCK_TOKENS} + 1 AS n_blocks FROM totals)",
        f"parted AS (SELECT *, CAST(floor(weight * CAST((SELECT sum(source_tokens) FROM totals) AS DOUBLE) * {MIXTURE['budget_share']}) AS BIGINT) AS part FROM weighed)",
        "placed AS (SELECT s.*, w.source_tokens, w.weight, w.part, n_blocks, CAST('0x' || substr(h, 1, 15) AS BIGINT) % n_blocks AS block FROM sized s JOIN parted w USING (source))",
        f"keyed AS (SELECT *, CAST('0x' || substr(o, 1, 15) AS BIGINT) % (n_blocks // {mixing.SPAN_BLOCKS} + 1) AS span FROM (SELECT source, block, sum(tokens) AS t, md5('{MIXTURE['seed']}/' || block) AS o, any_value(n_blocks) AS n_blocks FROM placed GROUP BY 1, 2) q)",
        "blocks AS (SELECT source, block, row_number() OVER o AS block_rank, CAST(sum(t) OVER (o ROWS UNBOUNDED PRECEDING) - t AS BIGINT) AS before FROM keyed WINDOW o AS (PARTITION BY source ORDER BY span, o, block))",
        "ranked AS (SELECT p.*, block_rank, before + CAST(sum(tokens) OVER (PARTITION BY p.source, p.block ORDER BY h, doc_id, tokens ROWS UNBOUNDED PRECEDING) AS BIGINT) - tokens AS start FROM placed p JOIN blocks b ON p.source = b.source AND p.block = b.block)",
    ]
    return f"WITH {', '.join(parts)} SELECT doc_id, source, CAST(tokens AS BIGINT) AS tokens, source_tokens, round(weight, 9) AS weight, CAST(block AS BIGINT) AS block, CAST(block_rank AS BIGINT) AS block_rank, start, CAST(part // greatest(source_tokens, 1) + CASE WHEN start < part % greatest(source_tokens, 1) THEN 1 ELSE 0 END AS BIGINT) AS copies FROM ranked"


def oracle_sql() -> dict[str, str]:
    groups = "(PARTITION BY t)"
    return {
        "op1_exact_dedup": f"SELECT doc_id, max(doc_id) OVER {groups} AS keep_id, count(*) OVER {groups} AS group_size, doc_id = max(doc_id) OVER {groups} AS kept, sha256(t) AS text_sha256 FROM (SELECT doc_id, {_LOWER} AS t FROM documents) q",
        "op3_source_mixing": _mixing_sql(),
        "op4_licence_scan": _licence_sql(),
        "op5_warc_archive": f"SELECT page_id, payload_bytes, sha1(p) AS payload_digest, CASE WHEN payload_bytes >= {warc.REVISIT_FROM} AND page_id <> last THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN payload_bytes >= {warc.REVISIT_FROM} AND page_id <> last THEN last END AS refers_to FROM (SELECT page_id, p, CAST(strlen(p) AS BIGINT) AS payload_bytes, max(page_id) OVER (PARTITION BY p) AS last FROM (SELECT page_id, coalesce(html, '') AS p FROM pages) a) b",
    }
