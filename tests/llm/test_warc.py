import gzip
import hashlib
import random

from jointsem.llm.store import new_folder
from jointsem.llm.warc import member, read_archives, salvage, write_archives


def sha(b):
    return hashlib.sha256(b).hexdigest()


def test_round_trip(spark):
    rows = [(1, "http://a/1", "x" * 200), (5, "http://a/5", "x" * 200), (3, "http://a/3", "y" * 99), (4, "http://a/4", "y" * 99), (6, None, None), (7, "http://ü/7", ""), (8, "u", "é" * 50), (2, "v", "é" * 50), (2, "v", "é" * 50), (None, "n", "x" * 200), (9, "long", "z\0\r\n\r\n" * 300_000)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 as payload", "2 as record_type")
    folder = new_folder(spark, "t")
    write_archives(pages, folder, archive_records=2)
    got = sorted((str(r.page_id), r.url, r.payload_bytes, r.payload_digest, r.type, r.refers_to) for r in read_archives(spark, folder).collect())
    first = {"x" * 200: 1, "é" * 50: 2, rows[-1][2]: 9}
    want = []
    for i, u, h in rows:
        f = first.get(h)
        again = f is not None and (i is None or i > f)
        want.append((str(i), u or "", len((h or "").encode()), sha((h or "").encode()), "revisit" if again else "response", f if again else None))
    assert got == sorted(want)
    payloads = {r.page_id: r.payload for r in read_archives(spark, folder, payload=True).where("type = 'response'").collect()}
    assert payloads[9] == rows[-1][2].encode() and payloads[6] == b""


def test_salvage_recovers_what_follows_damage():
    rng = random.Random(6)
    bodies = [bytes(rng.randrange(256) for _ in range(rng.randrange(50, 400))) for _ in range(12)]
    members = [member(i, "u", "response", None, b, sha(b)) for i, b in enumerate(bodies)]
    broken = bytearray(members[3])
    broken[len(broken) // 2] ^= 0x55
    wrong = member(5, "u", "response", None, bodies[5], sha(b"other"))
    plain = gzip.decompress(members[7])
    parts = [members[0], b"\0\0", members[1], b"garbage WARC/1.1\r\n junk \x1f\x8b\x08 ", members[2], bytes(broken), members[4], wrong, members[6], plain, plain[:60], members[8], members[9][: len(members[9]) // 2]]
    data = b"".join(parts)
    found = salvage(data)
    assert [int(r.headers["warc-record-id"][10:-1]) for r in found.records] == [0, 1, 2, 4, 6, 7, 8]
    assert all(r.payload == bodies[int(r.headers["warc-record-id"][10:-1])] for r in found.records)
    covered = sorted([(r.at, r.at + r.size) for r in found.records] + [g[:2] for g in found.gaps])
    assert covered[0][0] == 0 and covered[-1][1] == len(data)
    assert all(a[1] == b[0] or set(data[a[1] : b[0]]) == {0} for a, b in zip(covered[:-1], covered[1:], strict=True))
    assert len(found.gaps) == 5 and any("digest" in g[2] for g in found.gaps)


def test_empty_inputs(spark):
    assert salvage(b"").records == [] and salvage(b"nothing here").gaps == [(0, 12, "no version line")]
    folder = new_folder(spark, "t")
    write_archives(spark.createDataFrame([], "page_id long, url string, html string"), folder)
    assert read_archives(spark, folder).collect() == []
