"""The registered queries: their columns, their SQL, and brute force where SQL can't say the same."""

import hashlib
import zlib

import duckdb
import numpy as np
import pytest

import corpus_pipeline
from prefbook.llm.bin_packing import PARAMETERS, Encoder
from prefbook.llm.pii import find, listed
from prefbook.llm.queries import ORACLES, QUERIES
from prefbook.llm.warc_derive import derivatives, response_record

from .test_secret_scan import expected as secrets_of

COLUMNS = {
    "op1_prefix_targets": "conv_id bigint, n_turns bigint, turns_sha256 string, loss_chars bigint, loss_sha256 string, formatted_chars bigint",
    "op2_repetition_coverage": "doc_id bigint, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, base_failed boolean, kept boolean",
    "op3_disguised_pii": "doc_id bigint, n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, spans string",
    "op5_minimum_bin_slack": "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint, sequence_id bigint, offset bigint",
    "op7_token_group_join": "doc_id bigint, n_shingles bigint, component_id bigint",
    "op8_shift_table_search": "doc_id bigint, n_words bigint, n_hit bigint, n_items bigint, items_sha256 string, contaminated boolean",
    "op9_rendezvous_shards": "doc_id bigint, size bigint, text_crc32 bigint, law string, shard int, slot bigint, grown_shard int",
    "op10_entropy_secrets": "doc_id bigint, n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, spans string",
}


@pytest.fixture(scope="module")
def rows(spark, small):
    kept = {}

    def of(name):
        if name not in kept:
            kept[name] = QUERIES[name](spark, small).collect()
        return kept[name]

    return of


@pytest.fixture(scope="module")
def texts(spark, small):
    return {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text").collect()}


def test_one_query_for_each_operator():
    assert sorted(int(n[2:].split("_")[0]) for n in QUERIES if n.startswith("op")) == list(range(1, 11))
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "near_duplicates", "decontamination", "secrets", "packing"]


@pytest.mark.parametrize("name", sorted(COLUMNS))
def test_columns(spark, small, name):
    kinds = dict(QUERIES[name](spark, small).dtypes)
    for column in COLUMNS[name].split(", "):
        c, kind = column.split(" ")
        assert kinds[c] == kind


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_sql(rows, small, name):
    con = duckdb.connect()
    for t in ("documents", "conversations", "benchmark"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    want = con.execute(ORACLES[name])
    names = [x[0] for x in want.description]
    show = lambda rows: sorted(tuple(str(x) for x in row) for row in rows)
    assert show(tuple(r[n] for n in names) for r in rows(name)) == show(want.fetchall())


def test_added_conversation(rows):
    r = next(r for r in rows("op1_prefix_targets") if r.conv_id == -7)
    text = "</s>[INST] ok [/INST]"
    assert r.n_turns == 2 and r.loss_chars == len(text) and r.loss_sha256 == hashlib.sha256(text.encode()).hexdigest()
    assert r.turns_sha256 == hashlib.sha256(f"user\n{text}\nassistant\n{text}\n".encode()).hexdigest()


def test_personal_data(rows, texts):
    for r in rows("op3_disguised_pii"):
        base, added = find(texts[r.doc_id])
        assert r.base_sha256 == hashlib.sha256(listed(base).encode()).hexdigest() and r.spans == listed({k: base[k] + added[k] for k in base})


def test_secrets(rows, texts):
    for r in rows("op10_entropy_secrets"):
        assert (r.n_assign, r.n_access, r.n_hex, r.base_sha256, r.spans) == secrets_of(texts[r.doc_id])


def test_packing(rows, texts):
    slow = Encoder(PARAMETERS).slow
    own = {}
    for r in rows("op5_minimum_bin_slack"):
        own.setdefault(r.doc_id, []).append(r)
    for i, t in texts.items():
        ids = np.array([*slow.encode(t, add_special_tokens=False).ids, 0], dtype="<u4")
        at = 0
        for r in sorted(own[i], key=lambda r: r.piece):
            assert r.start == at and r.ids_crc32 == zlib.crc32(ids[at : at + r.length].tobytes())
            at += r.length
        assert at == len(ids)
    assert len({r.sequence_id for v in own.values() for r in v}) <= -(-sum(r.length for v in own.values() for r in v) // 2048) + 1


def test_derivatives(spark, small, rows):
    made = {(r.page_id, r.kind): r for r in rows("op6_warc_derivatives")}
    for page in spark.read.parquet(f"{small}/pages.parquet").collect():
        for headers, block in derivatives(response_record(page.url, page.html)):
            r = made[page.page_id, dict(headers)["WARC-Type"]]
            assert r.block_sha256 == hashlib.sha256(block).hexdigest() and r.refers_to == dict(headers)["WARC-Refers-To"]


def test_shards(rows, texts):
    assert all(r.text_crc32 == zlib.crc32(texts[r.doc_id].encode()) for r in rows("op9_rendezvous_shards"))
