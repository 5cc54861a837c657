import base64
import hashlib
import io
import random
import zlib

from linform.llm import warc as W


def b32(x):
    return base64.b32encode(hashlib.sha1(x.encode()).digest()).decode()


def test_round_trip(spark):
    rng = random.Random(5)
    rows = [(i, f"http://x/{i}", f"<p>{i % 13} é🙂\r\n\r\nWARC/1.1\r\n" * rng.randrange(1, 4)) for i in range(60)]
    rows += [(100, None, None), (101, "u v\n", ""), (None, "n", "lone"), (None, "n", rows[0][2]), (7, "again", rows[7][2]), (200, "big", "xyz " * 400_000)]
    rows += [(1000 + i, "h", "hot page") for i in range(300)]
    df = spark.createDataFrame([(*r, True) for r in rows], "page_id long, url string, html string, revisit boolean").repartition(4)
    got = W.archive_pages(spark, df).collect()
    assert not [r for r in got if r.kind != "record"]
    best = {}
    for p, _, h in rows:
        if p is not None:
            best[h or ""] = max(best.get(h or "", p), p)
    want = sorted(((p, len((h or "").encode()), b32(h or ""), *(("response", None) if best.get(h or "", p) == p else ("revisit", best[h or ""]))) for p, _, h in rows), key=str)
    assert sorted(((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in got), key=str) == want
    assert W.archive_pages(spark, df.limit(0)).count() == 0


def archive(n, zipped):
    parts = [W.build_record(i, f"http://x/{i}", f"body {i} ".encode() * 50, False, None) for i in range(n)]
    if not zipped:
        return parts
    out = []
    for p in parts:
        c = zlib.compressobj(6, zlib.DEFLATED, 31)
        out.append(c.compress(p) + c.flush())
    return out


def read(data):
    records, gaps, covered = [], [], 0
    for kind, start, end, _, _, *rest in W.salvage(io.BytesIO(data), len(data)):
        assert start == covered and end > start
        covered = end
        (records if kind == "record" else gaps).append(W.page_of(rest[0]["warc-record-id"]) if kind == "record" else (start, end, rest[0]))
    assert covered == len(data)
    return records, gaps


def test_salvage():
    for zipped in (True, False):
        parts = archive(9, zipped)
        whole = b"".join(parts)
        assert read(whole) == (list(range(9)), [])
        starts = [sum(map(len, parts[:i])) for i in range(10)]
        hurt = bytearray(whole)
        for at in range(starts[3] + len(parts[3]) // 2, starts[3] + len(parts[3]) // 2 + 20):
            hurt[at] ^= 0x55
        assert read(bytes(hurt))[0] == [0, 1, 2, 4, 5, 6, 7, 8] and [g[:2] for g in read(bytes(hurt))[1]] == [(starts[3], starts[4])]
        cut = whole[: starts[8] + 30]
        assert read(cut)[0] == list(range(8)) and read(cut)[1][0][:2] == (starts[8], len(cut))
        junk = b"junk\x1f\x8b\x08 WARC/ more"
        mixed = whole[: starts[2]] + junk + whole[starts[2] :]
        assert read(mixed)[0] == list(range(9)) and [g[:2] for g in read(mixed)[1]] == [(starts[2], starts[2] + len(junk))]
        assert read(junk + whole)[0] == list(range(9))
        lost = whole[: starts[5] + 7] + whole[starts[6] :]
        assert read(lost)[0] == [0, 1, 2, 3, 4, 6, 7, 8]
    assert read(b"") == ([], []) and read(b"nothing here")[1][0][:2] == (0, 12)


def test_random_damage_keeps_whole_records():
    rng = random.Random(2)
    for zipped in (True, False):
        parts = archive(12, zipped)
        starts = [sum(map(len, parts[:i])) for i in range(13)]
        for _ in range(60):
            data = bytearray(b"".join(parts))
            bad = set()
            for _ in range(rng.randrange(1, 4)):
                at = rng.randrange(len(data))
                data[at] ^= 1 << rng.randrange(8)
                bad.add(max(i for i in range(12) if starts[i] <= at))
            got, _ = read(bytes(data))
            assert set(range(12)) - bad <= set(got)


def zipped(data):
    c = zlib.compressobj(6, zlib.DEFLATED, 31)
    return c.compress(data) + c.flush()


def regions(data):
    """Ids of records, gaps, and whether the regions cover the file."""
    ids, gaps, covered, last = [], [], 0, (0, 0)
    for kind, start, end, a, b, *rest in W.salvage(io.BytesIO(data), len(data)):
        assert start == covered or (start, end) == last
        covered, last = max(covered, end), (start, end)
        if kind == "record":
            ids.append(W.page_of(rest[0]["warc-record-id"]))
        else:
            gaps.append((start, end, a, b, rest[0]))
    assert covered == len(data)
    return ids, gaps


def test_members_of_several_records(monkeypatch):
    parts = archive(6, False)
    starts = [sum(map(len, parts[:i])) for i in range(7)]
    for keep in (W.KEEP, 100):  # kept from the first pass, and inflated again through the window
        monkeypatch.setattr(W, "KEEP", keep)
        whole = zipped(b"".join(parts))
        assert regions(whole * 2) == ([*range(6)] * 2, [])
        wrong = parts[3].replace(b"body 3", b"bodi 3", 1)
        data = zipped(b"".join([*parts[:3], wrong, *parts[4:]]))
        assert regions(data) == ([0, 1, 2, 4, 5], [(0, len(data), starts[3], starts[4], "wrong digest")])
        for cut in (20, 8, 5, 1):  # of the last record, or of the checksum only
            ids, gaps = regions(whole[:-cut] + whole)
            assert ids[-6:] == list(range(6)) and ids[:-6] in (list(range(5)), list(range(6))) and gaps
            ids, gaps = regions(whole[:-cut])
            assert ids in (list(range(5)), list(range(6))) and gaps[-1][4] == "cut off member"
        hurt = bytearray(whole)
        hurt[-6] ^= 1  # the checksum
        ids, gaps = regions(bytes(hurt) + parts[0])
        assert ids == [*range(6), 0] and [g[4] for g in gaps] == ["broken member"]
        rest = zipped(b"".join(parts[:2]) + b"noise" + parts[2])
        assert regions(rest) == ([0, 1, 2], [(0, len(rest), starts[2], starts[2] + 5, "no version line")])
        bare = parts[0].replace(b"WARC-Block-Digest", b"WARC-Other-Digest")
        assert regions(zipped(bare)) == ([0], []) and regions(zipped(bare + parts[1])[:-3])[0] == [1]


def test_random_damage_in_members_of_several_records():
    rng = random.Random(9)
    parts = [W.build_record(i, f"http://x/{i}", rng.randbytes(3000).hex().encode(), False, None) for i in range(8)]
    whole = zipped(b"".join(parts[:4])) , zipped(b"".join(parts[4:]))
    for _ in range(40):
        data = bytearray(b"".join(whole))
        at = rng.randrange(len(whole[0]))
        data[at] ^= 1 << rng.randrange(8)
        ids, gaps = regions(bytes(data))
        assert ids[-4:] == [4, 5, 6, 7] and ids[:-4] == sorted(ids[:-4]) and (gaps or ids == list(range(8)))
        before = sum(len(zipped(b"".join(parts[:i]))) + 400 < at for i in range(1, 4))  # records inflated before the damage
        assert set(range(before)) <= set(ids)


def test_a_large_member_is_read_through_a_window(monkeypatch):
    monkeypatch.setattr(W, "KEEP", 1 << 20)
    rng = random.Random(1)
    body = rng.randbytes(1 << 18)
    data = zipped(b"".join(W.build_record(i, "http://x", body + bytes([i]), False, None) for i in range(40)))
    seen, most = [], 0
    member = W.Inflated(W.Bytes(io.BytesIO(data), len(data)), 0)
    for row in member.rows():
        seen.append(W.page_of(row[3]["warc-record-id"]))
        most = max(most, len(member.window))
    assert seen == list(range(40)) and most < 3 * W.STEP and member.size > 10 << 20


def test_archives_are_spread_over_tasks(spark):
    listed = spark.createDataFrame([(f"p{i}", 60 << 20, 5) for i in range(37)], "path string, bytes long, records long").coalesce(1)
    assert W.spread(listed).rdd.getNumPartitions() == 37
    assert W.spread(listed.limit(0)).rdd.getNumPartitions() == 1


def test_damaged_file_through_spark(spark, tmp_path):
    parts = archive(6, True)
    (tmp_path / "a.warc.gz").write_bytes(parts[0] + parts[1][:40] + b"".join(parts[2:]))
    listed = spark.createDataFrame([(f"file://{tmp_path}/a.warc.gz",)], "path string")
    rows = W.read_archives(listed, payloads=True).collect()
    assert [r.page_id for r in rows if r.kind == "record"] == [0, 2, 3, 4, 5]
    assert [(r.start, r.end) for r in rows if r.kind == "gap"] == [(len(parts[0]), len(parts[0]) + 40)]
    assert bytes(rows[0].payload) == b"body 0 " * 50


def test_headers_of_any_length():
    pages = [W.build_record(i, "http://x/" + "\x01" * n, b"body", False, None) for i, n in enumerate((3, 70_000, 5, 900_000, 1))]
    zipped = []
    for p in pages:
        c = zlib.compressobj(6, zlib.DEFLATED, 31)
        zipped.append(c.compress(p) + c.flush())
    for parts in (pages, zipped):
        assert read(b"".join(parts)) == ([0, 1, 2, 3, 4], [])
    cut = pages[0] + pages[1][:150_000]
    assert read(cut) == ([0], [(len(pages[0]), len(cut), "no end of header")])
