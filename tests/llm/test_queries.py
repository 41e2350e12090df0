"""The registered queries on the smallest tables: SQL where there is any, the contract's columns and rows elsewhere."""

import glob
import hashlib
import os
import zlib

import duckdb
import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import __spark_entry__
from subgraph_engine.llm import langid, merkle, queries
from tests.test_queries import same

SF = "/root/testdata/sf0.001"
COLUMNS = {
    "op1_packing": "doc_id start length ids_crc32 doc_tokens sequence_id offset", "op2_urls": "page_id host path rule verdict", "op3_bpe": "doc_id n_tokens ids_sha256 decoded_sha256",
    "op4_merkle": "doc_id n_chars edited_sha256 fingerprint edited_fingerprint near_edited near_next", "op5_chat": "conv_id n_turns turns_sha256 loss_chars loss_sha256 formatted_chars",
    "op6_neardup": "doc_id n_shingles component_id kept", "op8_toxicity": "doc_id held_out score predicted", "op9_quality": "doc_id n_words word_chars n_symbols n_dup_lines n_repeat_words base_failed kept",
    "op10_lm": "doc_id held_out n_tokens n_known train_tokens base_score score", "op7_language": "doc_id language confidence kept", "page_language": "page_id language confidence kept",
}


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM read_parquet('{f}')")
    return con


@pytest.fixture(scope="module")
def texts(duck):
    return dict(duck.execute("SELECT doc_id, coalesce(text, '') FROM documents").fetchall())


@pytest.mark.parametrize("name", sorted(COLUMNS))
def test_query(spark, duck, texts, name):
    got = __spark_entry__.queries()[name](spark, SF)
    rows = got.collect()
    assert set(COLUMNS[name].split()) <= set(got.columns) and rows
    if name in queries.oracle_sql():
        cur = duck.execute(queries.oracle_sql()[name])
        columns = [d[0] for d in cur.description]
        order = sorted(columns)
        assert sorted(got.columns) == order
        assert same([tuple(r[c] for c in order) for r in rows]) == same([tuple(r[columns.index(c)] for c in order) for r in cur.fetchall()])
    elif name == "op3_bpe":
        reference = Tokenizer.from_file(public_tokenizers.path(queries.VOCABULARY))
        want = {}
        for i, text in texts.items():
            ids = reference.encode(text, add_special_tokens=False).ids
            want[i] = len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(reference.decode(ids, skip_special_tokens=False).encode()).hexdigest()
        assert {r["doc_id"]: tuple(r)[1:] for r in rows} == want
    elif name == "op4_merkle":
        order = sorted(texts, reverse=True)
        for r in rows:
            mine, after = texts[r["doc_id"]], texts[order[(order.index(r["doc_id"]) + 1) % len(order)]]
            assert r["n_chars"] == len(mine) and r["edited_sha256"] == hashlib.sha256(merkle.edited(mine, after).encode()).hexdigest()
            assert 0.4 <= r["near_edited"] <= 1 and (r["near_next"] == 1) == (mine == after)
    elif name == "op8_toxicity":
        assert {r["doc_id"]: r["held_out"] for r in rows} == {i: zlib.crc32(str(i).encode()) % 4 == 2 for i in texts}
        assert all(r["predicted"] == (r["score"] >= 0.3) and 0 <= r["score"] <= 1 for r in rows)
    elif name == "op10_lm":
        assert {r["doc_id"]: r["held_out"] for r in rows} == {i: zlib.crc32(str(i).encode()) % 7 == 2 for i in texts}
    elif name == "op1_packing":
        assert {r["doc_id"] for r in rows} == set(texts) and sum(r["length"] for r in rows) == sum({r["doc_id"]: r["doc_tokens"] for r in rows}.values())


def brute_languages(model, rows):
    """The fusion in plain numpy: rows of text, host and declared language."""
    names, n = model.languages, len(model.languages)

    def normal(x):
        x = np.exp(x - x.max())
        return x / x.sum()

    logs = [model.likelihoods(pa.array([t], pa.string()))[0] for t, _, _ in rows]
    hosts, domains, total = {}, {}, np.ones(n)
    for x, (_, host, _) in zip(logs, rows, strict=True):
        total = total + normal(x)
        if host is not None:
            hosts[host] = hosts.get(host, 0) + normal(x)
    for host, x in hosts.items():
        domain = ".".join(host.split(".")[-2:])
        domains[domain] = domains.get(domain, 0) + x
    overall, out = total / total.sum(), []
    for x, (_, host, says) in zip(logs, rows, strict=True):
        prior = overall
        if host is not None:
            d = domains[".".join(host.split(".")[-2:])]
            of_domain = (d + langid.DOMAIN_PRIOR * overall) / (d.sum() + langid.DOMAIN_PRIOR)
            prior = (hosts[host] + langid.HOST_PRIOR * of_domain) / (hosts[host].sum() + langid.HOST_PRIOR)
        x = x + np.log(prior)
        suffix = langid.SUFFIXES.get(host.split(".")[-1]) if host else None
        for said, right in ((says, langid.MARKUP_RIGHT), (suffix, langid.SUFFIX_RIGHT)):
            if said in names:
                x = x + np.where(np.array(names) == said, np.log(right), np.log((1 - right) / (n - 1)))
        p = normal(x)
        out.append((names[int(p.argmax())], float(p.max())))
    return out


def test_language_equals_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    model = langid.train_text(docs)
    hosts = ["www.one.de", "one.de", "a.shop.fr", "b.shop.fr", "plain.com", None]
    rows = [(k, r["text"], hosts[k % 6], [None, "fr", "en", "xx"][k % 4]) for k, r in enumerate(docs.orderBy("doc_id").limit(120).collect())]
    rows += [(500, None, None, None), (501, "", "one.de", None), (502, "12 345 !", "plain.com", "es")]
    frame = spark.createDataFrame([(i, t, h, f"<html lang='{s}'>" if s else None) for i, t, h, s in rows], "doc_id long, text string, source string, page string")
    got = {r["doc_id"]: r for r in langid.identify(frame, model, markup_col="page").collect()}
    for (i, *_), (language, sure) in zip(rows, brute_languages(model, [(t, h, s) for _, t, h, s in rows]), strict=True):
        assert got[i]["language"] == language and got[i]["confidence"] == pytest.approx(sure, rel=1e-6)
        assert got[i]["kept"] == (language != langid.UNKNOWN and sure >= langid.CERTAIN)


def test_languages_of_documents_not_learned_from(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("text is not null and text <> ''")
    held = (F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4) == 2
    judged = langid.identify(docs.where(held), langid.train_text(docs.where(~held))).join(docs.select("doc_id", "lang"), "doc_id").collect()
    assert len(judged) > 150 and sum(r["language"] == r["lang"] for r in judged) >= 0.98 * len(judged)


def test_pages_of_no_kind(spark):
    """Page judgement needs no text, no host and no markup."""
    model = langid.train_text(spark.read.parquet(f"{SF}/documents.parquet"))
    pages = spark.createDataFrame([(None, None, None, None), (1, "", "", ""), (1, "", "", ""), (2, None, "x.de", "<html")], "page_id long, bare string, host string, html string")
    got = langid.identify(pages, model, id_col="page_id", text_col="bare", host_col="host", markup_col="html").collect()
    assert len(got) == 4 and all(0 <= r["confidence"] <= 1 for r in got)
    assert langid.identify(pages.limit(0), model, id_col="page_id", text_col="bare", host_col="host", markup_col="html").count() == 0
