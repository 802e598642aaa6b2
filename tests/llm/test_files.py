import gzip
import random

import pytest

from halograph.llm import chat, warc
from halograph.llm.common import Scratch
from oracle import check

SF = "/root/testdata/sf0.001"
PAGES = "page_id long, url string, html string, digest string"


@pytest.fixture
def parts_of(spark):
    """Makes the file sources cut files into parts of so many bytes."""
    names = ("spark.sql.files.maxPartitionBytes", "spark.sql.files.openCostInBytes")
    before = [spark.conf.get(n) for n in names]

    def cut(size):
        spark.conf.set(names[0], str(size))
        spark.conf.set(names[1], "0")

    yield cut
    for n, v in zip(names, before):
        spark.conf.set(n, v)


def test_round_trip_with_magic_inside_payloads(spark, tmp_path, parts_of):
    trap = "WARC/1.1\r\nWARC-Type: response\r\nContent-Length: 10\r\n\r\n0123456789\r\n\r\n" * 3 + "y" * 80
    big = "z" * 120
    rows = [(5, "http://a", big, "x"), (2, "http://b", big, None), (9, None, big, None), (1, "http://c\r\nX: y", trap, None), (3, "u", None, None), (4, "u", "", None), (6, "u", "short", None), (7, "u", "short", None), (8, "u", "é" * 60, None), (2, "http://b", big, None), (None, "n", big, None)]
    path = warc.write_warc(spark.createDataFrame(rows, PAGES), str(tmp_path / "w"), files=2)
    for size in (400, 3000, 1 << 20):
        parts_of(size)
        got = warc.read_warc(spark, path).collect()
        assert len(got) == len(rows) and all(r.sound for r in got)
        kinds = sorted((r.record_id, r.record_type, r.refers_to) for r in got)
        assert ("<urn:page:2>", "response", None) in kinds and ("<urn:page:5>", "revisit", "<urn:page:2>") in kinds and ("<urn:page:none>", "revisit", "<urn:page:2>") in kinds
        assert ("<urn:page:6>", "response", None) in kinds and ("<urn:page:7>", "response", None) in kinds
        payload = {r.record_id: bytes(r.payload).decode() for r in got if r.record_type == "response"}
        assert payload["<urn:page:1>"] == trap and payload["<urn:page:8>"] == "é" * 60 and payload["<urn:page:3>"] == ""


def test_members_and_broken_chains(spark, tmp_path):
    record = lambda body: b"WARC/1.0\r\nWARC-Type: resource\r\nWARC-Record-ID: <urn:page:1>\r\nContent-Length: %d\r\n\r\n%s\r\n\r\n" % (len(body), body)
    (tmp_path / "a.warc.gz").write_bytes(gzip.compress(record(b"one")) + gzip.compress(record(b"two")))
    (tmp_path / "b.warc").write_bytes(record(b"three") + b"garbage" + record(b"lost"))
    (tmp_path / "c.warc").write_bytes(record(b"whole") + record(b"cut short")[:-8])
    (tmp_path / "d.warc").write_bytes(b"no record\r\n\r\n" + record(b"never"))
    got = warc.read_warc(spark, str(tmp_path)).collect()
    assert sorted(bytes(r.payload) for r in got if r.sound) == [b"one", b"three", b"two", b"whole"]
    broken = {r.path.rsplit("/", 1)[-1]: (r.offset, r.record_id) for r in got if not r.sound}
    assert broken == {"b.warc": (len(record(b"three")), None), "c.warc": (len(record(b"whole")), "<urn:page:1>"), "d.warc": (0, None)}


def test_records_that_cross_parts_and_fakes_at_their_heads(spark, tmp_path, parts_of):
    """Payloads that end in line ends, hold whole records, or are longer than a part."""
    fake = "WARC/1.1\r\nWARC-Type: response\r\nWARC-Record-ID: <urn:page:666>\r\nContent-Length: 4\r\n\r\nfake\r\n\r\n"
    rng = random.Random(3)
    rows = []
    for k in range(60):
        body = "".join(rng.choice([fake, "\r\n", "\r\n\r\n", "\r", "text " * 20, "WARC/1.1\r\n", fake[:60]]) for _ in range(rng.randint(0, 12)))
        rows.append((k, f"http://h/{k}", f"{k}:" + body, None))
    rows.append((60, "u", fake * 300, None))
    path = warc.write_warc(spark.createDataFrame(rows, PAGES), str(tmp_path / "w"), files=1)
    for size in (900, 5000):
        parts_of(size)
        got = warc.read_warc(spark, path).collect()
        assert sorted((r.record_id, bytes(r.payload).decode()) for r in got) == sorted((f"<urn:page:{i}>", h) for i, _, h, _ in rows) and all(r.sound for r in got)


def test_long_headers_and_odd_lengths(spark, tmp_path, parts_of):
    odd = [f"WARC/1.1\r\nContent-Length: {n}\r\n\r\nabc\r\n\r\n" for n in ("²", "9" * 5000, "-1", "")]
    rows = [(1, "http://a", "x", None), (2, "data:," + "u" * 100_000, "y", None), (3, "http://b", "".join(odd), None), (4, "http://c", "WARC/1.1\r\n" * 20_000, None), (5, "http://d", "z", None)]
    path = warc.write_warc(spark.createDataFrame(rows, PAGES).coalesce(1), str(tmp_path / "w"), files=1)
    for size in (60_000, 1 << 20):
        parts_of(size)
        got = {r.record_id: r for r in warc.read_warc(spark, path).collect()}
        assert len(got) == len(rows) and all(r.sound for r in got.values())
        for i, url, html, _ in rows:
            assert (got[f"<urn:page:{i}>"].target_uri, bytes(got[f"<urn:page:{i}>"].payload).decode()) == (url, html)


def test_no_pages(spark, tmp_path):
    path = warc.write_warc(spark.createDataFrame([], PAGES), str(tmp_path / "none"))
    assert warc.read_warc(spark, path).count() == 0


def test_warc_query(spark):
    check(spark, SF, warc.op8_warc, warc.OP8_SQL)


MESSAGES = [
    (1, 0, "user", "Hello there\nhow are you?"), (1, 1, "assistant", "I am fine."), (1, 2, "user", "Another topic"), (1, 3, "user", "> I am fine.\nGood to hear"),
    (1, 4, "assistant", "> > I am fine.\n>  Good to hear\nYes  \n> Another topic"), (1, 5, "user", "> HELLO   there\n> how are you?\nSame"), (1, 6, "user", ">   good to HEAR\nquoting a reply"),
    (2, 0, "user", None), (2, 3, None, "> nothing here"), (2, 7, "user", ">>x\n>x\nx"), (2, 5000, "user", "far later"), (3, -4097, "user", "x"), (3, -1, "user", ">x"), (3, -1, "user", ">x"),
]
SCHEMA = "conv_id long, turn long, role string, text string"


def test_chat_against_sql(spark, tmp_path):
    import duckdb

    path = str(tmp_path / "conversations.parquet")
    c = duckdb.connect()
    c.sql("CREATE TABLE t (conv_id BIGINT, turn BIGINT, role VARCHAR, text VARCHAR)")
    c.executemany("INSERT INTO t VALUES (?, ?, ?, ?)", MESSAGES)
    c.sql(f"COPY t TO '{path}' (FORMAT parquet)")
    from oracle import rows

    got = chat.op9_chat_format(spark, str(tmp_path))
    d = duckdb.connect()
    d.sql(f"CREATE VIEW conversations AS SELECT * FROM read_parquet('{path}')")
    want = d.sql(chat.OP9_SQL)
    assert rows(got.columns, [tuple(r) for r in got.collect()]) == rows(list(want.columns), want.fetchall())


def test_chat_edges(spark):
    df = spark.createDataFrame([(None, 1, "u", "a"), (1, None, "u", "> b"), (1, 2, None, None)], SCHEMA)
    got = {(r.conv_id, r.turn): r for r in chat.format_chat(df).collect()}
    assert got[None, 1].head is None and got[1, None].reply_to is None and got[1, 2].content == "" and got[1, 2].role == "unknown"
    assert chat.format_chat(df.limit(0)).count() == 0


def test_chat_threads(spark):
    got = {r.turn: r for r in chat.format_chat(spark.createDataFrame([m for m in MESSAGES if m[0] == 1], SCHEMA)).collect()}
    assert (got[3].reply_to, got[3].head, got[3].content) == (1, 1, "Good to hear")
    assert (got[5].reply_to, got[5].head) == (0, 0) and got[2].reply_to == 1 and not got[2].quotes
    assert (got[6].reply_to, got[6].head) == (3, 1)  # quotes a reply: the same chain


def test_transcripts_in_reply_order(spark, monkeypatch):
    monkeypatch.setattr(chat, "SPAN", 2)
    out = chat.format_chat(spark.createDataFrame([(*m, "x") for m in MESSAGES if m[0] == 1], SCHEMA + ", position string"))
    assert [r.turn for r in out.orderBy("position").collect()] == [0, 5, 1, 3, 6, 2, 4] and sorted(r.position for r in out.collect()) == list(range(7))
    blocks = {r.block: r.text for r in chat.transcripts(out, 4).collect()}
    assert sorted(blocks) == [0, 1] and blocks[0].startswith("<|user|>\nHello there\nhow are you?\n<|end|>\n<|user|>\nSame") and ">" not in blocks[1].replace("|>", "")


def test_scratch_is_removed(spark):
    import os

    s = Scratch(spark)
    s.keep(spark.range(3), "t")
    s.drop()
    assert not os.path.exists(s.root)
