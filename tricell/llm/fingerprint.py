"""Canonical exact digests of documents, in DataFrame functions only.

The canonical form of a text is its Unicode composition (NFC), with case folded
in full and each run of white space (Unicode's White_Space) as one space and
none at the ends.  Composition and folding are by the ICU library that Spark
ships, called only for texts outside ASCII.  Its
fingerprint is 128 bits wide: two xxhash64 values that start from different
seeds.  Rows with equal fingerprints are compared byte by byte, so two
different canonical forms never share a group.

Defined results: a null text reads as empty; an empty text has the fingerprint
of the empty form; repeated rows share a group; an empty table gives no rows;
columns named like an output give way, other names never clash.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .ranges import id_cells
from .storage import free_name, materialise

# Fixed salts of the two halves of a fingerprint.
_SALTS = ("first half", "second half")
# White space outside ASCII, as a character class.
_WIDE_BLANKS = r"\x{85}\x{A0}\x{1680}\x{2000}-\x{200A}\x{2028}\x{2029}\x{202F}\x{205F}\x{3000}"


def canonical(text: Column) -> Column:
    """The canonical form of a text."""
    plain = F.octet_length(text) == F.char_length(text)
    icu = lambda owner, call, s, option: F.reflect(F.lit(f"com.ibm.icu.{owner}"), F.lit(call), s, F.lit(option))
    # folding takes texts apart first, as marks under case change otherwise depend on how they were composed
    folded = icu("lang.UCharacter", "foldCase", icu("text.Normalizer", "decompose", text, False), True)
    composed = icu("text.Normalizer", "compose", folded, False)
    spaced = F.when(plain, F.lower(text)).otherwise(F.regexp_replace(composed, f"[{_WIDE_BLANKS}]", " "))
    for blank in "\t\n\x0b\x0c\r":
        spaced = F.replace(spaced, F.lit(blank), F.lit(" "))
    # most texts hold no two blanks in a row, so the pattern is the exception
    return evaluated_once(spaced, lambda s: F.trim(F.when(F.contains(s, F.lit("  ")), F.regexp_replace(s, " +", " ")).otherwise(s)))


def evaluated_once(value: Column, use: Callable[[Column], Column]) -> Column:
    """`use(value)`, where `value` is computed once though `use` may name it often."""
    return F.transform(F.array(value), use)[0]


def digest(form: Column) -> Column:
    """128 bits of a canonical form, in hexadecimal."""
    half = lambda salt, s: F.lpad(F.lower(F.hex(F.xxhash64(F.lit(salt), s))), 16, "0")
    return evaluated_once(form, lambda s: F.concat(*[half(salt, s) for salt in _SALTS]))


def collisions(docs: DataFrame, digests: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(fingerprint, form, variant) of each canonical form that shares its digest with a lesser form.

    `digests` has id and fingerprint of all of `docs`.  Only documents whose
    digest occurs twice are read again; each is compared with one representative
    of its digest.  The result is empty unless the hash collides.
    """
    repeated = digests.groupBy("fingerprint").agg(F.count("*").alias("n"), F.min("id").alias("rep")).where("n > 1")
    # stored, so that the join may split the members of a digest that many share
    repeated = materialise(repeated.select("fingerprint", "rep"), "repeated")
    pairs = digests.join(repeated, "fingerprint").select("fingerprint", "id", "rep")
    texts = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    members = texts.join(pairs.select("id", "fingerprint", "rep").distinct(), "id").withColumn("form", canonical(F.col("text")))
    # rows that share an id may differ in text, so the digest is checked again
    members = materialise(members.where(digest(F.col("form")) == F.col("fingerprint")).select("fingerprint", "form", (F.col("id") == F.col("rep")).alias("chosen")), "forms")
    rep = materialise(members.where("chosen").groupBy("fingerprint").agg(F.min("form").alias("rep_form")), "rep-forms")
    odd = members.join(rep, "fingerprint").where("form <> rep_form")
    order = Window.partitionBy("fingerprint").orderBy("form")
    return odd.select("fingerprint", "form").distinct().withColumn("variant", F.row_number().over(order))


def colliding_forms(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame | None:
    """The stored `collisions` among the texts of `docs`; None if there are none."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    digests = materialise(docs.select(F.col(id_col).alias("id"), digest(canonical(text)).alias("fingerprint")), "digests")
    clashes = materialise(collisions(docs, digests, id_col, text_col), "collisions")
    return None if clashes.isEmpty() else clashes


def with_fingerprint(docs: DataFrame, clashes: DataFrame | None, text_col: str = "text", name: str = "fingerprint") -> DataFrame:
    """`docs` with the fingerprint of a text column; a form of `clashes` carries its variant after a colon.

    A column of `docs` of that name gives way.
    """
    docs = docs.select([c for c in docs.columns if c.lower() != name.lower()])
    text = F.coalesce(F.col(text_col), F.lit(""))
    hashed = docs.withColumn(name, digest(canonical(text)))
    if clashes is None:
        return hashed
    own, its_digest, its_form, variant = (free_name(hashed, x) for x in ("own_form", "clash_digest", "clash_form", "clash_variant"))
    named = clashes.select(F.col("fingerprint").alias(its_digest), F.col("form").alias(its_form), F.col("variant").alias(variant))
    joined = hashed.withColumn(own, canonical(text)).join(named, (F.col(name) == F.col(its_digest)) & (F.col(own) == F.col(its_form)), "left")
    marked = F.when(F.col(variant).isNotNull(), F.concat(name, F.lit(":"), F.col(variant))).otherwise(F.col(name))
    return joined.withColumn(name, marked).select(*docs.columns, name)


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """`docs` with a column `fingerprint`; equal fingerprints mean equal canonical forms.

    A form that lost its digest to another one in the table carries its variant after a colon.
    A column of `docs` named fingerprint gives way to this one.
    """
    return with_fingerprint(docs, colliding_forms(docs, id_col, text_col), text_col)


def duplicate_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fingerprint, group_id, copies): documents of equal canonical form, by their least id."""
    marked = fingerprints(docs.select(id_col, text_col), id_col, text_col).select(id_col, "fingerprint")
    groups = marked.groupBy("fingerprint").agg(F.min(id_col).alias("group_id"), F.count("*").alias("copies"))
    return marked.join(groups, "fingerprint").select(id_col, "fingerprint", "group_id", "copies")


def with_next(docs: DataFrame, id_col: str, payload: list[str], rows_per_bucket: int = 20_000) -> DataFrame:
    """`docs` with `next_<column>` of the following row by id; the last row is followed by the first.

    Ids are cut in runs of about `rows_per_bucket` rows by exact counts, so that
    clustered ids do not meet in one task.  Inside a run the next row is found
    by a window; the first row of each run, one row a run, is also dealt to the
    end of the run before.  Null ids come first; rows that tie on id follow each
    other by payload.  Columns of `docs` named next_<column> give way.
    """
    docs = docs.select([c for c in docs.columns if c not in {f"next_{x}" for x in payload}])
    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.lit(1).alias("weight"))
    deal, buckets = id_cells(slim, rows_per_bucket)
    bucket, end = free_name(docs, "bucket"), free_name(docs, "end")
    dealt = deal(docs, id_col, bucket).withColumn(end, F.lit(False))
    order = [F.col(end), F.col(id_col).asc_nulls_first(), *[F.col(c).asc_nulls_first() for c in payload]]
    inside = Window.partitionBy(bucket).orderBy(*order)
    first = F.min(F.struct(F.col(id_col).isNotNull().alias("named"), F.col(id_col).alias("id"), *[F.col(c).alias(f"head_{i}") for i, c in enumerate(payload)]))
    heads = dealt.groupBy(bucket).agg(first.alias("head"))
    carried = {c: F.col("head")[f"head_{i}"] for i, c in enumerate(payload)}
    ends = heads.select(
        *[(carried[c] if c in carried else F.lit(None).cast(docs.schema[c].dataType)).alias(c) for c in docs.columns],
        F.pmod(F.col(bucket) - 1, F.lit(buckets).cast("long")).alias(bucket), F.lit(True).alias(end),
    )
    following = [F.lead(c).over(inside).alias(f"next_{c}") for c in payload]
    return dealt.unionByName(ends).select("*", *following).where(~F.col(end)).drop(bucket, end)
