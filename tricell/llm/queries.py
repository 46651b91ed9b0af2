"""The thin queries over the operators of this subpackage, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import fingerprint, host_rules, mixing, near_dup, packing, qda, secrets_crf, site_lines, toxicity, warc
from .storage import materialise


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near-duplicate groups of documents on word pairs."""
    return near_dup.near_duplicates(_table(spark, sf_dir, "documents"), config=near_dup.NearDupConfig(width=2))


def op2_host_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Document rules and host verdicts; a document's source is its host."""
    judged = host_rules.apply_host_rules(_table(spark, sf_dir, "documents"))
    return judged.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept",
        F.col("docs").alias("host_docs"), F.col("failed").alias("host_failed"),
    )


def op3_canonical_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of documents and of their edited texts."""
    docs = _table(spark, sf_dir, "documents").select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    clashes = fingerprint.colliding_forms(docs)
    rows = fingerprint.with_next(fingerprint.with_fingerprint(docs, clashes), "doc_id", ["text", "fingerprint"])
    n = F.char_length("text")
    cut = F.floor(n / 4).cast("int")
    rows = rows.withColumn("n_chars", n.cast("long")).withColumn("edited", F.concat(F.substring("text", F.lit(1), n - cut), F.substring("next_text", F.lit(1), cut)))
    own, edited = fingerprint.canonical(F.col("text")), fingerprint.canonical(F.col("edited"))
    rows = fingerprint.with_fingerprint(rows, clashes, "edited", "edited_fingerprint")
    # the forms are compared only where the fingerprints agree
    same = F.when(F.col("fingerprint") != F.col("edited_fingerprint"), 0.0).when(own == edited, 1.0).otherwise(0.0)
    return rows.select(
        "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), "fingerprint", "edited_fingerprint",
        same.alias("near_edited"), (F.col("fingerprint") == F.col("next_fingerprint")).cast("double").alias("near_next"),
    )


def op4_site_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What line dedup leaves of each document; a document's source is its host."""
    cut = site_lines.drop_boilerplate(_table(spark, sf_dir, "documents"))
    return cut.select("doc_id", "n_lines", "n_dropped", F.char_length("text").cast("long").alias("chars_left"), F.sha2("text", 256).alias("text_sha256"))


def op5_warc_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Write all pages as WARC records and read the archives back."""
    base = warc.write_archive(_table(spark, sf_dir, "pages"))
    records = materialise(warc.read_archive(spark, base).drop("payload"), "records")
    return warc.resolved(records).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def _fold(modulus: int):
    """The remainder that deals documents to folds; -1, never held out, for a null id."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % modulus, F.lit(-1))


def op6_quality_qda(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality of all documents, learnt outside the held-out fold."""
    labels = _table(spark, sf_dir, "labels").where(_fold(5) != 0)
    table = qda.statistics_table(_table(spark, sf_dir, "documents"))
    config = qda.QdaConfig()
    scored = qda.score(table, qda.fit(table, labels, config=config)).withColumnRenamed("id", "doc_id")
    return scored.select("doc_id", (_fold(5) == 0).alias("held_out"), "score", (F.col("score") >= config.threshold).cast("int").alias("predicted"))


def op7_secret_field(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Secrets of all documents: fixed patterns and the field's additions."""
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    found = secrets_crf.find_secrets(docs, model=secrets_crf.fit(docs))
    joined = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")

    def number(kind: str):
        return F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")

    counts = [number(k) for k in secrets_crf.KINDS[:3]]
    base = F.filter("spans", lambda s: s["kind"] != "crf")
    return found.select("doc_id", *counts, F.sha2(joined(base), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"))


def op8_variable_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents packed into sequences of 512 to 4096 words."""
    return packing.pack_texts(_table(spark, sf_dir, "documents"))


def op9_mix_to_budget(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sources mixed to 150% of all words."""
    docs = _table(spark, sf_dir, "documents").select("doc_id", "source", mixing.word_count("text").alias("size"))
    mixed = mixing.mix(materialise(docs, "sizes"))
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def op10_toxic_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity of all documents, learnt outside the held-out fold."""
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    config = toxicity.ToxicityConfig()
    model = toxicity.fit(docs, _table(spark, sf_dir, "labels").where(_fold(4) != 2), config=config)
    scored = toxicity.score_documents(docs, model, keep=["doc_id"])
    score = F.col("toxicity")
    return scored.select("doc_id", (_fold(4) == 2).alias("held_out"), score.alias("score"), (score >= config.threshold).cast("int").alias("predicted"))


QUERIES = {
    "op1_minhash_near_dedup": op1_minhash_near_dedup,
    "op2_host_quality_rules": op2_host_quality_rules,
    "op3_canonical_fingerprint": op3_canonical_fingerprint,
    "op4_site_line_dedup": op4_site_line_dedup,
    "op5_warc_archive": op5_warc_archive,
    "op6_quality_qda": op6_quality_qda,
    "op7_secret_field": op7_secret_field,
    "op8_variable_best_fit": op8_variable_best_fit,
    "op9_mix_to_budget": op9_mix_to_budget,
    "op10_toxic_neighbours": op10_toxic_neighbours,
}

_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"

SQL = {
    "op1_minhash_near_dedup": rf"""
with recursive w as (
    select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as words
    from documents),
pos as (select doc_id, words, unnest(range(1, greatest(len(words), 2))) as i from w where len(words) > 0),
g as (select distinct doc_id, case when len(words) = 1 then [words[1]] else [words[i], words[i + 1]] end as gram from pos),
n as (select doc_id, count(*) as n from g group by doc_id),
p as (select x.doc_id as a, y.doc_id as b, count(*) as shared from g x join g y on x.gram = y.gram and x.doc_id < y.doc_id group by 1, 2),
l as (select a, b from p join n na on na.doc_id = a join n nb on nb.doc_id = b where 100 * shared >= 80 * (na.n + nb.n - shared)),
s as (select a, b from l union all select b, a from l),
reach(id, r) as (select doc_id, doc_id from documents union select s.b, reach.r from reach join s on reach.id = s.a),
c as (select id, min(r) as component_id from reach group by id)
select d.doc_id, cast(coalesce(n.n, 0) as bigint) as n_shingles, c.component_id, d.doc_id = c.component_id as kept
from documents d join c on c.id = d.doc_id left join n on n.doc_id = d.doc_id
""",
    "op2_host_quality_rules": r"""
with w as (select doc_id, source, coalesce(text, '') as text, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as words from documents),
pos as (select doc_id, words, unnest(range(1, len(words) - 1)) as i from w where len(words) >= 3),
tri as (select doc_id, i, count(*) over (partition by doc_id, words[i], words[i + 1], words[i + 2]) as n from pos),
rep as (select doc_id, count(distinct i + k) as n from (select doc_id, i, unnest([0, 1, 2]) as k from tri where n >= 2) group by doc_id),
lines as (select doc_id, line, count(*) as n from (select doc_id, unnest(string_split(text, chr(10))) as line from w) where regexp_matches(line, '[^\x20\x09-\x0D]') group by doc_id, line),
dup as (select doc_id, sum(n - 1) as n from lines group by doc_id),
b as (select w.doc_id, source, len(words) as n_words, coalesce(list_sum(list_transform(words, lambda x: length(x))), 0) as word_chars,
    length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) as n_symbols, coalesce(dup.n, 0) as n_dup_lines, coalesce(rep.n, 0) as n_repeat_words
    from w left join dup using (doc_id) left join rep using (doc_id)),
f as (select *, n_words < 50 or 100 * n_repeat_words > 50 * n_words as base_failed from b),
h as (select source, count(*) as docs, count(*) filter (where base_failed) as failed from f group by source),
t as (select sum(docs)::double as n, sum(failed)::double as k, count(*) as hosts, sum(docs * docs)::double as q from h),
s as (select sum(docs * pow(failed / docs - k / n, 2)) as s from h, t),
m as (select n, k / n as mean, case when hosts > 1 then (s - (hosts - 1) * (k / n) * (1 - k / n)) / greatest(n - q / n, 1e-9) else 0 end as between_hosts from t, s),
p as (select mean, case when not (mean > 0 and mean < 1) then 1 when between_hosts > 1e-12 then least(greatest(mean * (1 - mean) / between_hosts - 1, 1), n) else n end as weight from m)
select doc_id, cast(n_words as bigint) as n_words, cast(word_chars as bigint) as word_chars, cast(n_symbols as bigint) as n_symbols,
    cast(n_dup_lines as bigint) as n_dup_lines, cast(n_repeat_words as bigint) as n_repeat_words, base_failed,
    not base_failed and (failed + mean * weight) / (docs + weight) < 0.6 as kept, cast(docs as bigint) as host_docs, cast(failed as bigint) as host_failed
from f join h on f.source is not distinct from h.source, p
""",
    "op4_site_line_dedup": r"""
with d as (select doc_id, source, text, string_split(text, chr(10)) as lines from documents),
pages as (select distinct source, text from documents where text is not null),
total as (select source, count(*) as n from pages group by source),
held as (select distinct source, text, trim(unnest(string_split(text, chr(10))), ' ' || chr(9) || chr(13)) as line from pages),
freq as (select source, line, count(*) as n from held where line <> '' group by source, line),
boiler as (select f.source, list(f.line) as dropped from freq f join total t on f.source is not distinct from t.source where f.n >= 4 and f.n > 0.1::double * t.n group by f.source),
c as (select doc_id, lines, text, list_filter(lines, lambda x: trim(x, ' ' || chr(9) || chr(13)) = '' or b.dropped is null or not list_contains(b.dropped, trim(x, ' ' || chr(9) || chr(13)))) as stay
    from d left join boiler b on d.source is not distinct from b.source)
select doc_id, cast(coalesce(len(list_filter(lines, lambda x: trim(x, ' ' || chr(9) || chr(13)) <> '')), 0) as bigint) as n_lines,
    cast(coalesce(len(lines) - len(stay), 0) as bigint) as n_dropped, cast(length(array_to_string(stay, chr(10))) as bigint) as chars_left,
    sha256(array_to_string(stay, chr(10))) as text_sha256
from c
""",
    "op5_warc_archive": r"""
with p as (select page_id, coalesce(html, '') as html, sha1(coalesce(html, '')) as hex from pages),
b as (select page_id, html, hex, array_to_string(list_transform(string_split(hex, ''),
    lambda x: substr('0000000100100011010001010110011110001001101010111100110111101111', 4 * (position(x in '0123456789abcdef') - 1) + 1, 4)), '') as bits from p),
d as (select page_id, html, hex, array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    1 + 16 * cast(substr(bits, cast(5 * i + 1 as bigint), 1) as integer) + 8 * cast(substr(bits, cast(5 * i + 2 as bigint), 1) as integer)
    + 4 * cast(substr(bits, cast(5 * i + 3 as bigint), 1) as integer) + 2 * cast(substr(bits, cast(5 * i + 4 as bigint), 1) as integer)
    + cast(substr(bits, cast(5 * i + 5 as bigint), 1) as integer), 1)), '') as payload_digest from b),
f as (select *, min(page_id) over (partition by html) as first_page from d)
select page_id, cast(strlen(html) as bigint) as payload_bytes, payload_digest,
    case when page_id = first_page then 'response' else 'revisit' end as record_type,
    case when page_id = first_page then null else first_page end as refers_to
from f
""",
}
