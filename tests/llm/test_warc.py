import os
import random

import pytest

from seqcount.llm import warc


def archive(n, seed=0, compress=True):
    rng = random.Random(seed)
    records = [warc.record(i, f"http://x/{i}", bytes(rng.randrange(256) for _ in range(rng.randint(0, 400))) + (b"WARC/1.1\r\n" if i % 4 == 0 else b""), None if i % 3 else i - 1) for i in range(1, n + 1)]
    parts = [warc.member(r) for r in records] if compress else records
    starts = [sum(map(len, parts[:i])) for i in range(n + 1)]
    return b"".join(parts), starts


@pytest.mark.parametrize("compress", [True, False])
def test_sound_archives_read_whole(compress):
    data, starts = archive(30, compress=compress)
    rows = list(warc.salvage(data))
    assert [r["kind"] for r in rows] == ["record"] * 30
    assert [r["offset"] for r in rows] == starts[:-1] and sum(r["length"] for r in rows) == len(data)
    assert [warc.page_of(r["record_id"]) for r in rows] == list(range(1, 31))


@pytest.mark.parametrize("compress", [True, False])
@pytest.mark.parametrize("seed", range(12))
def test_damage_costs_only_the_records_that_it_touches(compress, seed):
    rng = random.Random(seed)
    data, starts = archive(25, seed, compress)
    hurt = set()
    body = bytearray(data)
    for _ in range(rng.randint(1, 4)):
        at, n = rng.randrange(len(body)), rng.randint(1, 60)
        for i in range(at, min(len(body), at + n)):
            body[i] ^= rng.randint(1, 255)
        hurt |= {k + 1 for k in range(25) if starts[k] < min(len(body), at + n) and starts[k + 1] > at}
    rows = list(warc.salvage(bytes(body)))
    found = {warc.page_of(r["record_id"]) for r in rows if r["kind"] == "record"}
    assert set(range(1, 26)) - hurt <= found
    assert sum(r["length"] for r in rows) == len(body)
    edges = [(r["offset"], r["offset"] + r["length"]) for r in rows]
    assert all(a[1] == b[0] for a, b in zip(edges, edges[1:]))
    if compress:  # a member's checksum covers the header too; in a plain record only the block has a digest
        assert found == set(range(1, 26)) - hurt and any(r["kind"] == "gap" and r["reason"] for r in rows)


def test_cut_garbage_and_empty():
    data, starts = archive(5)
    assert list(warc.salvage(b"")) == []
    assert [r["kind"] for r in warc.salvage(data[:-3])] == ["record"] * 4 + ["gap"]
    assert [r["kind"] for r in warc.salvage(b"noise" + data)] == ["gap"] + ["record"] * 5
    assert [r["kind"] for r in warc.salvage(b"\x1f\x8b\x08 no" * 3)] == ["gap"]
    plain, _ = archive(2, compress=False)
    assert [r["kind"] for r in warc.salvage(data + plain)] == ["record"] * 7


def test_round_trip_of_rows(spark, tmp_path):
    rows = [(1, "http://a", "same"), (2, "http://b", "same"), (3, None, None), (4, "u r\r\nl", ""), (5, "c", "é<html>"), (6, "d", "x" * 300_000), (None, "e", "same"), (None, "f", "lonely"), (7, "g", "twin"), (7, "g", "twin")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 as n", "2 as first").repartition(3)
    for compress in (True, False):
        folder = f"file://{tmp_path}/{compress}"
        manifest = warc.archive_pages(pages, folder, compress=compress)
        got = warc.read_archives(manifest, folder).collect()
        assert {r["kind"] for r in got} == {"record"}
        view = sorted(((warc.page_of(r["record_id"]), r["payload_bytes"], r["payload_digest"], r["type"], warc.page_of(r["refers_to_id"])) for r in got), key=repr)
        digest = lambda t: warc.sha1_digest((t or "").encode())
        size = lambda t: len((t or "").encode())
        want = [(1, None), (2, 1), (3, None), (4, 3), (5, None), (6, None), (None, 1), (None, None), (7, None), (7, None)]
        assert view == sorted([(p, size(t), digest(t), "response" if f is None else "revisit", f) for (p, f), (_, _, t) in zip(want, rows)], key=repr)
        payloads = {r["payload_digest"]: r["payload"] for r in got if r["type"] == "response"}
        assert payloads[digest("é<html>")] == "é<html>".encode()
        again = warc.read_warc(spark, folder).where("kind = 'record'").count()
        assert again == len(rows) and len(os.listdir(f"{tmp_path}/{compress}")) >= 1
    least = warc.archive_pages(pages, f"file://{tmp_path}/least", least_bytes=5)
    kinds = {warc.page_of(r["record_id"]): r["type"] for r in warc.read_archives(least, f"file://{tmp_path}/least").collect()}
    assert kinds[2] == "response" and kinds[4] == "response"
    empty = warc.archive_pages(pages.limit(0), f"file://{tmp_path}/none")
    assert warc.read_archives(empty, f"file://{tmp_path}/none").count() == 0
