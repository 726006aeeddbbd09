import hashlib

import duckdb
import pytest

from bundlemv.llm import warc

PAGES = "page_id long, url string, html string, key string, n int"


def pages_of(spark):
    big = "é<p>" * 400
    rows = [
        (1, "http://a/1", big), (2, "http://a/2", big), (9, "http://a/9\r\nX: y", big), (3, None, "small"), (4, "http://a/4", "small"),
        (5, "u", None), (6, "u", ""), (7, "u v é", "WARC/1.1\r\n\r\n" * 200), (8, "u", "x" * 999), (10, "u", "x" * 999), (11, "u", "y" * 1000),
        (11, "u", "y" * 1000), (12, "u", "y" * 1000), (12, "u", "y" * 1000), (None, "n", big), (None, None, "z" * 2000), (None, None, "z" * 2000), (13, "long", "q\n" * 400_000),
    ]
    return spark.createDataFrame([(*r, "k", 0) for r in rows], PAGES)


@pytest.mark.parametrize("compression", ["none", "gzip"])
def test_round_trip(spark, tmp_path, compression):
    pages, path = pages_of(spark).repartition(4), f"file://{tmp_path}/w"
    warc.archive_pages(pages, path, compression=compression)
    got = spark.read.format("warc").option("verify", "true").load(path).collect()
    want = sorted(((r.page_id is None, r.page_id or 0), (r.html or "").encode()) for r in pages.collect())
    assert sorted(((r.page_id is None, r.page_id or 0), hashlib.sha1(r.payload).hexdigest() if r.record_type == "response" else r.payload_digest) for r in got) == sorted((i, hashlib.sha1(b).hexdigest()) for i, b in want)
    kinds = sorted((r.page_id or -1, r.record_type, r.refers_to_page) for r in got)
    assert [k for k in kinds if k[1] == "revisit"] == [(-1, "revisit", 9), (1, "revisit", 9), (2, "revisit", 9), (11, "revisit", 12), (11, "revisit", 12)]
    assert {r.page_id: r.payload_bytes for r in got}[13] == 800_000
    assert all(r.http_status == 200 and r.payload_digest == hashlib.sha1(r.payload).hexdigest() for r in got if r.record_type == "response")
    by_id = {r.page_id: r for r in got}
    assert by_id[1].refers_to == by_id[9].record_id and by_id[1].payload_bytes == 1999 - 399 + 400


def test_pushdown_and_pruning(spark, tmp_path):
    path = f"file://{tmp_path}/w"
    warc.archive_pages(pages_of(spark), path)
    some = spark.read.format("warc").schema("page_id long, record_type string").load(path).where("record_type = 'revisit' and page_id > 1")
    plan = some._jdf.queryExecution().executedPlan().toString()
    assert "Filter (" not in plan and "(record_type" not in plan.split("BatchScan")[0]
    assert sorted(r.page_id for r in some.collect()) == [2, 11, 11]
    found = spark.read.format("warc").load(path).where("target_uri like 'http://a/%' and payload_bytes > 1500 and record_type in ('response')")
    assert [r.page_id for r in found.collect()] == [9]
    assert spark.read.format("warc").load(path).where("target_uri is null").count() == 3


def test_damage_is_noticed(spark, tmp_path):
    warc.archive_pages(pages_of(spark).coalesce(1), f"file://{tmp_path}/w")
    file = next((tmp_path / "w").glob("*.warc"))
    file.write_bytes(file.read_bytes().replace(b"small", b"smell"))
    with pytest.raises(Exception, match="digest"):
        spark.read.format("warc").option("verify", "true").load(f"file://{tmp_path}/w").collect()


def test_uncommitted_files_are_unseen(spark, tmp_path):
    warc.archive_pages(pages_of(spark).limit(3), f"file://{tmp_path}/w")
    (tmp_path / "w" / "left.warc").write_bytes(b"half a record")
    assert spark.read.format("warc").load(f"file://{tmp_path}/w").count() == 3
    warc.archive_pages(pages_of(spark).limit(0), f"file://{tmp_path}/empty")
    assert spark.read.format("warc").load(f"file://{tmp_path}/empty").count() == 0


def test_files_roll_over(spark, tmp_path):
    warc.register(spark)
    warc.classify(pages_of(spark)).coalesce(1).write.format("warc").mode("append").option("filebytes", "2000").save(f"file://{tmp_path}/w")
    assert len(list((tmp_path / "w").glob("*.warc"))) > 3
    assert spark.read.format("warc").load(f"file://{tmp_path}/w").count() == pages_of(spark).count()


def test_sql(spark, tiny):
    con = duckdb.connect()
    con.execute(f"create view pages as from '{tiny}/pages.parquet'")
    cols = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
    assert sorted(con.execute(f"select {', '.join(cols)} from ({warc.OP3_SQL})").fetchall()) == sorted(tuple(r) for r in warc.op3(spark, tiny).select(cols).collect())
