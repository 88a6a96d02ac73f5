"""Chat formatting, WARC and licence digests: exact round trips and SQL."""

import hashlib
import io
import re

import duckdb
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from modelsort.llm import catalog, chat, licences, warc

TURNS = "conv_id long, turn long, role string, text string, block string"
PIECES = ["<", "|", "\\", "<|", "<\\", "<|end|>\n", "<|turn|>", "<|text|>", "a", "é", "東", "\n", " "]


@settings(max_examples=80, deadline=None)
@given(st.lists(st.tuples(st.sampled_from(["user", "assistant", "", "<|turn|>"]), st.lists(st.sampled_from(PIECES), max_size=12).map("".join)), min_size=1, max_size=6))
def test_assembly_is_reversible(turns):
    import pyarrow as pa

    out, at, start, stop = chat.assemble(pa.array([r for r, _ in turns]), pa.array([t for _, t in turns]))
    text = out.tobytes()
    assert chat.parse(text.decode()) == turns
    for k, (_, t) in enumerate(turns):
        assert chat.unescape(text[start[k] : stop[k]].decode()) == t


def test_conversations_read_back(spark):
    rows = [(1, 1, "assistant", "b <|end|> é", "x"), (1, 0, "user", None, "x"), (None, 0, None, "lost", "x"), (2, 700, "assistant", "late", "x"), (2, 0, "assistant", "early " * 50_000, "x"), (2, 0, "assistant", "early " * 50_000, "x"), (1, None, "system", "first\\", "x")]
    found = {r["conv_id"]: r for r in chat.read_back(chat.format_conversations(spark.createDataFrame(rows, TURNS).repartition(3))).collect()}
    order = {1: [("system", "first\\"), ("user", ""), ("assistant", "b <|end|> é")], None: [("", "lost")], 2: [("assistant", "early " * 50_000)] * 2 + [("assistant", "late")]}
    for conv, turns in order.items():
        r = found[conv]
        loss = "".join(t for role, t in turns if role == "assistant")
        assert r["n_turns"] == len(turns)
        assert r["turns_sha256"] == hashlib.sha256("".join(f"{a}\n{t}\n" for a, t in turns).encode()).hexdigest()
        assert (r["loss_chars"], r["loss_sha256"]) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
    assert chat.read_back(chat.format_conversations(spark.createDataFrame([], TURNS))).count() == 0


PAGES = "page_id long, url string, html string, payload string"


def test_archives_round_trip(spark):
    rows = [(1, "http://a", "same", "p"), (5, "http://b", "same", "p"), (3, None, None, "p"), (4, "http://c\r\nX: y", "", "p"), (7, "u", "né " * 100_000, "p"), (None, "n", "same", "p"), (None, "m", "alone", "p"), (9, "r", "twice", "p"), (9, "r", "twice", "p")]
    found = warc.read_archives(warc.write_archives(spark.createDataFrame(rows, PAGES).repartition(3)), keep_payload=True).collect()
    assert len(found) == len(rows)
    by = {}
    for r in found:
        by.setdefault((r["page_id"], r["payload_digest"]), []).append(r)
    for page_id, _, html, _ in rows:
        data = (html or "").encode()
        r = by[page_id, warc.base32_sha1(data)][0]
        assert r["payload_bytes"] == len(data)
        assert r["record_type"] == "revisit" or bytes(r["payload"]) == data
    kinds = {(r["page_id"], r["payload_bytes"]): (r["record_type"], r["refers_to"]) for r in found}
    assert kinds[1, 4] == ("revisit", 5) and kinds[5, 4] == ("response", None) and kinds[None, 4] == ("revisit", 5)
    assert kinds[3, 0] == ("revisit", 4) and kinds[4, 0] == ("response", None) and kinds[9, 5] == ("response", None) and kinds[None, 5] == ("response", None)
    assert warc.read_archives(warc.write_archives(spark.createDataFrame([], PAGES))).count() == 0


def test_revisits_of_one_payload_meet_their_response(spark, monkeypatch):
    monkeypatch.setattr(warc, "SALTS", 7)
    rows = [(i, f"u{i}", "same" if i % 3 else f"own {i}") for i in range(300)]
    records = warc.read_archives(warc.write_archives(spark.createDataFrame(rows, "page_id long, url string, html string").repartition(5))).cache()
    found = {r["page_id"]: (r["record_type"], r["refers_to"]) for r in warc.check_revisits(records).collect()}
    assert found == {i: ("revisit", 299) if i % 3 and i != 299 else ("response", None) for i in range(300)}
    for wrong in ({"payload_bytes": F.lit(5).cast("long")}, {"payload_digest": F.lit("A" * 32)}, {"refers_to": F.lit(0).cast("long")}):
        told = {k: F.when(F.col("page_id") == 7, v).otherwise(F.col(k)) for k, v in wrong.items()}
        with pytest.raises(warc.WarcError):
            warc.check_revisits(records.withColumns(told))
    records.unpersist()


def test_reader_refuses_broken_archives():
    good = warc.write_record(1, "u", b"hello world" * 1000, warc.base32_sha1(b"hello world" * 1000), None)
    assert [r.payload_bytes for r in warc.read_records(io.BytesIO(good * 3))] == [11_000] * 3
    wrong = warc.write_record(1, "u", b"hello", warc.base32_sha1(b"other"), None)
    for bad in (good[:-20], good + wrong, good[:40] + b"\0\0\0\0" + good[44:], b"junk" * 10):
        with pytest.raises((warc.WarcError, KeyError)):
            list(warc.read_records(io.BytesIO(bad)))


def plain_canonical(text):
    """The canonical form by words, for tests."""
    text = re.sub(licences.COPYRIGHT_LINE, " ", (text or "").lower())
    words = re.sub(licences.PUNCTUATION, " ", text).split(" ")
    line = "  ".join(w for w in words if w)
    for pattern, new in licences.spelling_patterns():
        line = re.sub(pattern, new.replace("{1}", r"\1").replace("{2}", r"\2"), f" {line} ").strip(" ")
    return line.replace("  ", " ")


def test_whole_licences_are_known_in_other_spelling(spark):
    known = licences.known_table(spark)
    found = {r["doc_id"]: r["license_id"] for r in licences.scan(catalog.with_variants(known), known.drop("n")).collect()}
    assert len(found) > 25 and found == {-n: name for n, name, _ in licences.known_texts()}
    assert {"GPL-3.0", "Apache-2.0", "MPL-2.0", "LGPL-2.1", "CC0-1.0"} <= set(found.values())


def test_spellings_stop_at_words(spark):
    texts = ["super center", "supercenter", "Centre, centre; CENTRES", "center center centers", "organise organisation organism emphasis emphasise", "sub-licence licence licenced", "per cent percentile", "a https://x whilst", "elabour labour", "élabour", "copyright owners", "reporganise", *(f"{b} {b}x x{b}" for b in licences.WORDS_CHANGED), "café centre naïve"]
    df = spark.createDataFrame(list(enumerate(texts)), "i int, t string")
    got = {r["i"]: r["c"] for r in df.select("i", licences.canonical(F.col("t")).alias("c")).collect()}
    assert got == {i: plain_canonical(t) for i, t in enumerate(texts)}
    assert got[0] != got[1] and got[2] == got[3] and got[4] == "organize organization organism emphasis emphasize" and got[5] == "sublicense license licensed" and got[8] == "elabour labor"


def test_licences(spark):
    mit = licences.KNOWN[0][1]
    variants = [mit, "Copyright (c) 2020 Someone\n\n" + mit.upper(), "  # Copyright 1999-2001, A. B.\nAll rights reserved.\n" + mit.replace("Software", "software").replace("sublicense", "sub-license"), mit + " and more", None, "", "©  2020\n", "released under the  MIT licence", "This work is licensed under the GNU General Public License, version 3.", "x " * 100_000]
    df = spark.createDataFrame([(i, t, "k") for i, t in enumerate(variants)], "doc_id long, text string, license_id string")
    found = {r["doc_id"]: r["license_id"] for r in licences.scan(df, licences.known_table(spark)).collect()}
    assert found == {0: "MIT", 1: "MIT", 2: "MIT", 3: None, 4: None, 5: None, 6: None, 7: "MIT", 8: "GPL-3.0-only", 9: None}
    assert licences.scan(df.limit(0), licences.known_table(spark)).count() == 0


@pytest.mark.parametrize("name", sorted(catalog.oracle_sql()))
def test_queries_equal_sql(spark, name):
    sf = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for t in ("documents", "benchmark", "pages", "conversations", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    found = catalog.queries()[name](spark, sf).toPandas()
    wanted = con.execute(catalog.oracle_sql()[name]).df()
    assert sorted(found.columns) == sorted(wanted.columns)
    plain = lambda df: sorted(tuple("None" if str(v) in ("None", "nan", "<NA>") else str(v).removesuffix(".0") for v in r) for r in df[sorted(df.columns)].itertuples(index=False))
    assert plain(found) == plain(wanted)
