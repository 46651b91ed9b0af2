"""The thin queries over whole tables, compared with plain rules; SQL compares those it can express."""

import hashlib
import re
import unicodedata
import zlib

import pytest

pytest.importorskip("tricell.llm")

from test_operators import reference_base, slow_targets  # noqa: E402

from tricell.llm import packing, queries, secrets_crf  # noqa: E402

WORD = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def documents(spark, sf_dir):
    return {r.doc_id: r for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()}


def by_id(df, documents):
    rows = df.collect()
    assert sorted(r.doc_id for r in rows) == sorted(documents)
    return {r.doc_id: r for r in rows}


def test_every_operator_has_its_query():
    assert sorted(int(name[2:].split("_")[0]) for name in queries.QUERIES) == list(range(1, 11))


@pytest.mark.parametrize("name", sorted(queries.SQL))
def test_query_equals_its_sql(spark, sf_dir, duck, name):
    df = queries.QUERIES[name](spark, sf_dir)
    columns = sorted(df.columns)
    cursor = duck.execute(queries.SQL[name])
    names = [c[0] for c in cursor.description]
    assert sorted(names) == columns
    rows = cursor.fetchall()
    assert rows and sorted(repr(tuple(r[c] for c in columns)) for r in df.collect()) == sorted(repr(tuple(r[names.index(c)] for c in columns)) for r in rows)


def plain_form(text):
    folded = unicodedata.normalize("NFC", unicodedata.normalize("NFD", text).casefold())
    return re.sub(r"[\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]+", " ", folded).strip(" ")


def test_fingerprints_of_documents_and_edited_texts(spark, sf_dir, documents):
    got = by_id(queries.op3_canonical_fingerprint(spark, sf_dir), documents)
    order = sorted(documents)
    prints, forms = {}, {}
    for at, i in enumerate(order):
        own, after = documents[i].text or "", documents[order[(at + 1) % len(order)]].text or ""
        cut = len(own) // 4
        edited = own[: len(own) - cut] + after[:cut]
        r = got[i]
        assert (r.n_chars, r.edited_sha256) == (len(own), hashlib.sha256(edited.encode()).hexdigest())
        for text, mark in ((own, r.fingerprint), (edited, r.edited_fingerprint)):
            assert prints.setdefault(plain_form(text), mark) == mark
            assert forms.setdefault(mark, plain_form(text)) == plain_form(text)
        assert r.near_edited == float(plain_form(own) == plain_form(edited))
        assert r.near_next == float(plain_form(own) == plain_form(after))


@pytest.mark.parametrize(("name", "modulus", "rest"), [("op6_quality_qda", 5, 0), ("op10_toxic_neighbours", 4, 2)])
def test_folds_and_scores(spark, sf_dir, documents, name, modulus, rest):
    got = by_id(queries.QUERIES[name](spark, sf_dir), documents)
    for i, r in got.items():
        assert r.held_out == (zlib.crc32(str(i).encode()) % modulus == rest)
        assert 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3)
    by_text = {}
    for i, r in got.items():
        assert by_text.setdefault(documents[i].text or "", r.score) == pytest.approx(r.score), "equal texts score alike"


def test_secrets_of_documents(spark, sf_dir, documents):
    got = by_id(queries.op7_secret_field(spark, sf_dir), documents)
    for i, r in got.items():
        text = documents[i].text or ""
        base = reference_base(text)
        marks = [f"{secrets_crf.KINDS[k]}:{s}:{e}" for s, k, e in base]
        assert [r.n_assign, r.n_access, r.n_hex] == [sum(k == n for _, k, _ in base) for n in range(3)]
        assert r.base_sha256 == hashlib.sha256(",".join(marks).encode()).hexdigest()
        spans = [x.split(":") for x in r.spans.split(",") if x]
        assert [":".join(x) for x in spans if x[0] != "crf"] == marks
        places = [(int(s), int(e)) for _, s, e in spans]
        assert [s for s, _ in places] == sorted(s for s, _ in places) and all(0 <= s < e <= len(text) for s, e in places)


def test_packed_documents(spark, sf_dir, documents):
    rows = queries.op8_variable_best_fit(spark, sf_dir).collect()
    pieces, bins = {}, {}
    for r in rows:
        pieces.setdefault(r.doc_id, []).append((r.start, r.length))
        if r.bin_id is not None:
            bins.setdefault(r.bin_id, []).append(r)
    assert sorted(pieces) == sorted(documents)
    for i, spans in pieces.items():
        at = 0
        for start, length in sorted(spans):
            assert start == at
            at += length
        assert at == len(WORD.findall(documents[i].text or ""))
    for members in bins.values():
        spans = sorted((r.bin_offset, r.bin_offset + r.length) for r in members)
        assert spans[0][0] == 0 and all(a[1] == b[0] for a, b in zip(spans, spans[1:]))
        assert members[0].used == spans[-1][1] and members[0].capacity == packing.least_length(spans[-1][1], packing.PackConfig())


def test_mixed_documents(spark, sf_dir, documents):
    got = by_id(queries.op9_mix_to_budget(spark, sf_dir), documents)
    sizes, taken = {}, {}
    for i, d in documents.items():
        sizes[d.source] = sizes.get(d.source, 0) + len(WORD.findall(d.text or ""))
        taken[d.source] = taken.get(d.source, 0) + got[i].taken
    targets = slow_targets(sizes, (3, 1, 2), 1.5, 2)
    for i, d in documents.items():
        r = got[i]
        assert r.size == len(WORD.findall(d.text or "")) and r.source_size == sizes[d.source]
        assert r.target == pytest.approx(targets[d.source])
        assert r.taken in {0, r.size, 2 * r.size}
    for s in sizes:
        # whole turns of the source, then the best subset of its documents
        own = [r.size for i, r in got.items() if documents[i].source == s]
        turns = int(targets[s] // sizes[s]) if sizes[s] else 0
        rest = round(targets[s] - turns * sizes[s])
        reach = 1
        for size in own:
            reach |= reach << size
        best = (reach & ((1 << (rest + 1)) - 1)).bit_length() - 1
        assert taken[s] == turns * sizes[s] + best
