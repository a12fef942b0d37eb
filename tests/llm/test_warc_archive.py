import base64
import gzip
import hashlib
import io
import zlib

from veil.llm import warc_archive as A
from veil.sources.shared import shared_path

PAGES = [
    (1, "http://a/", "one"), (2, "http://b/", "one"), (9, "http://c/", "one"), (3, None, None), (4, "http://d/\r\nX: y", ""), (5, "u", "WARC/1.1\r\nContent-Length: 5\r\n\r\nhello\r\n\r\n"),
    (6, "u", "é😀" * 50_000), (7, "u", "two\n"), (7, "u", "two\n"), (None, "u", "one"), (8, "u", "two"), (10, "v", "\r\n\r\n"),
]


def sha(t):
    return base64.b32encode(hashlib.sha1((t or "").encode()).digest()).decode()


def want(pages, least):
    rows = []
    for p, _, t in pages:
        t = t or ""
        n = len(t.encode())
        same = [q for q, _, x in pages if (x or "") == t and q is not None]
        top = max(same) if same and n >= least else p
        rows.append((p, n, sha(t), "response" if top == p else "revisit", None if top == p else top))
    return sorted(rows, key=str)


def test_round_trip_with_revisits(spark):
    df = spark.createDataFrame([(*p, "x") for p in PAGES], "page_id long, url string, html string, digest string")
    for least in (0, 4):
        got = A.archive(df, least)
        cols = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
        assert sorted(map(tuple, got.select(*cols).collect()), key=str) == want(PAGES, least)
    body = {r.page_id: bytes(r.payload).decode() for r in A.archive(df).filter("record_type = 'response'").collect()}
    assert body[9] == "one" and body[6] == "é😀" * 50_000 and body[5] == PAGES[5][2]


def test_files_are_bounded_and_standard(spark):
    noise = [hashlib.sha512(str(i % 40).encode()).hexdigest() * 4 for i in range(200)]
    df = spark.createDataFrame([(i, f"http://h/{i}", t) for i, t in enumerate(noise)], "page_id long, url string, html string")
    path = shared_path(spark, "t-warc")
    A.write(df.coalesce(1), path, file_bytes=8000)
    files = spark.read.format("binaryFile").load(path).collect()
    assert len(files) >= 10 and all(f.path.endswith(".warc.gz") and f.length <= 8000 for f in files)
    n = 0
    for f in files:
        kinds = []
        rest = bytes(f.content)
        while rest:  # each record can be read from its own member
            z = zlib.decompressobj(31)
            stream = io.BytesIO(z.decompress(rest))
            assert z.eof
            ((head, block),) = A.parse_stream(stream)
            kinds.append(head["warc-type"])
            assert head["warc-record-id"].startswith("<urn:uuid:") and int(head["content-length"]) == len(block)
            assert (head["warc-type"] == "revisit") == ("warc-refers-to" in head)
            rest = z.unused_data
        assert kinds[0] == "warcinfo" and "warcinfo" not in kinds[1:]
        n += len(kinds) - 1
    assert n == 200


def test_records_larger_than_a_file(spark):
    big = "0123456789abcdef" * (17 << 16)  # 17 MB, so the member does not end in a zero byte
    df = spark.createDataFrame([(1, "u", big), (2, "u", "small"), (3, "u", big)], "page_id long, url string, html string")
    path = shared_path(spark, "t-warc")
    A.write(df.coalesce(1), path, file_bytes=1000)
    got = {r.page_id: r for r in A.read(spark, path).collect()}
    assert bytes(got[3].payload).decode() == big and got[1].refers_to == 3 and got[1].payload_bytes == len(big) and bytes(got[2].payload) == b"small"
    for f in spark.read.format("binaryFile").load(path).collect():
        assert gzip.decompress(bytes(f.content)).startswith(b"WARC/1.1\r\nWARC-Type: warcinfo\r\n")


def test_empty_table(spark):
    assert A.archive(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0
