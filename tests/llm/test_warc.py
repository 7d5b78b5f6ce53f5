import glob
import hashlib
import struct

import zstandard as zstd

from motifjoin.llm import queries, warc


def brute(rows):
    least = {}
    for i, html in rows:
        body = (html or "").encode()
        if len(body) >= 100 and i is not None:
            least[body] = min(i, least.get(body, i))
    out = []
    for i, html in rows:
        body = (html or "").encode()
        ref = least.get(body) if i is not None and len(body) >= 100 else None
        again = ref is not None and ref != i
        out.append((i, len(body), hashlib.sha256(body).hexdigest(), "revisit" if again else "response", ref if again else None))
    return sorted(out, key=repr)


def test_query_equals_brute_force(spark, sf):
    rows = [(r.page_id, r.html) for r in spark.read.parquet(f"{sf}/pages.parquet").collect()]
    assert sorted(map(tuple, queries.op8_warc_archives(spark, sf).collect()), key=repr) == brute(rows)


def test_odd_rows_round_trip(spark, tmp_path):
    big = "é\r\n\r\nWARC/1.1\r\n" * 20
    rows = [(1, "u", big), (2, None, big), (3, "http://x/a b\r\nc", ""), (4, "u", None), (5, "u", "x" * 99), (6, "u", "x" * 99), (None, "n", big), (1, "u", big), (7, "u", "y" * 300_000), (8, "P*M\x18\0\0\0\0", "P*M\x18\0\0\0\0" * 50)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 as key", "2 as payload")
    warc.write_archives(df, str(tmp_path / "a"))
    got = warc.read_archives(spark, str(tmp_path / "a")).collect()
    assert sorted(((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in got), key=repr) == brute([(i, h) for i, _, h in rows])
    text = {r.page_id: r.payload for r in got if r.record_type == "response"}
    assert text[7] == b"y" * 300_000 and text[3] == b"" and text[1] == big.encode()
    warc.write_archives(df.limit(0), str(tmp_path / "b"))
    assert not glob.glob(str(tmp_path / "b/part-*")) or warc.read_archives(spark, str(tmp_path / "b")).count() == 0


def test_layout_of_an_archive(spark, sf, tmp_path):
    warc.write_archives(spark.read.parquet(f"{sf}/pages.parquet"), str(tmp_path / "a"))
    for name in glob.glob(str(tmp_path / "a/part-*")):
        data = open(name, "rb").read()
        magic, size = struct.unpack_from("<II", data)
        assert magic == 0x184D2A5D and size <= warc.DICTIONARY_BYTES
        first = 8 + size + len(warc.SEPARATOR)
        one = zstd.ZstdDecompressor(dict_data=zstd.ZstdCompressionDict(data[8 : 8 + size])).decompressobj().decompress(data[first:])
        assert one.startswith(b"WARC/1.1\r\n") and one.count(b"WARC-Type:") == 1


def test_dictionary_helps():
    records = [warc.record(i, f"http://h/{i}", f"<html><nav>same frame here</nav>{i * 7919}</html>".encode(), 45, "0" * 64, None, "1970-01-01T00:00:00Z") for i in range(400)]
    raw = warc.build_dictionary(records[:200])
    with_, without = zstd.ZstdCompressor(dict_data=zstd.ZstdCompressionDict(raw)), zstd.ZstdCompressor()
    assert sum(len(with_.compress(r)) for r in records[200:]) < 0.6 * sum(len(without.compress(r)) for r in records[200:])
