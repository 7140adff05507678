import hashlib
import zipfile
import zlib

import pyarrow.fs as pafs
import pytest

from viewsize.llm import media

SF = "/root/testdata/sf0.001"


def expected(text):
    raw = (text or "").encode()
    pay = raw + b"\0" * (max(64, -(-len(raw) // 64) * 64) - len(raw))
    return len(raw), len(pay), hashlib.sha256(pay).hexdigest(), zlib.crc32(pay[-64:])


def check(rows, texts):
    assert sorted((str(r["doc_id"]), r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) for r in rows) == sorted((str(d), *expected(t)) for d, t in texts)
    by = {}
    for r in rows:
        same = (r["media_bytes"], r["media_sha256"], r["feature"])
        assert by.setdefault(r["payload_sha256"], same) == same


def test_round_trip(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    check(media.media_features(docs).collect(), [(r["doc_id"], r["text"]) for r in docs.collect()])


def test_messy_rows(spark, messy, nothing):
    check(media.media_features(messy).collect(), [(r["doc_id"], r["text"]) for r in messy.collect()])
    assert media.media_features(nothing).collect() == []


@pytest.mark.parametrize("raw", [b"", b"x", b"y" * 64, bytes(range(256)) * 9])
def test_codec(raw):
    png = media.encode(media.pad(raw))
    assert media.decode(png) == media.pad(raw) and len(media.pad(raw)) % 64 == 0
    for bad in (png[:-20], png[:40] + bytes([png[40] ^ 1]) + png[41:], b"junk" + png):
        with pytest.raises(Exception):
            media.decode(bad)


def archive(tmp_path, n=40):
    path = tmp_path / "a.zip"
    with zipfile.ZipFile(path, "w", zipfile.ZIP_STORED) as z:
        for i in range(n):
            z.writestr(zipfile.ZipInfo(f"{i}.{i}.{i}"), media.encode(media.pad(bytes([65 + i % 26]) * (i * 37))))
    return path


def test_ranges_cover_every_member_once(spark, tmp_path):
    path = archive(tmp_path)
    for split in (97, 1000, 10**9):
        rows = media.read_archives(spark, str(tmp_path), splitbytes=str(split)).collect()
        assert sorted(int(r["member"].split(".")[0]) for r in rows) == list(range(40)) and all(r["error"] is None for r in rows)
        reader = media.ArchiveReader({"path": str(tmp_path), "splitbytes": str(split)})
        assert len(reader.partitions()) == -(-path.stat().st_size // split)


def test_a_damaged_member_fails_alone(spark, tmp_path):
    path = archive(tmp_path)
    with zipfile.ZipFile(path) as z:
        at = z.getinfo("7.7.7").header_offset
    raw = bytearray(path.read_bytes())
    raw[at + 60] ^= 255
    path.write_bytes(bytes(raw))
    rows = media.read_archives(spark, str(tmp_path), attempts="2").collect()
    assert [r["member"] for r in rows if r["error"]] == ["7.7.7"] and len(rows) == 40


def test_fetch_is_tried_again(tmp_path, monkeypatch):
    archive(tmp_path)
    calls, right = [], media.fetch

    def flaky(fs, path, offset, stored, crc, handle=None):
        calls.append(offset)
        if calls.count(offset) == 1:
            raise OSError("lost")
        return right(fs, path, offset, stored, crc, handle)

    monkeypatch.setattr(media, "fetch", flaky)
    reader = media.ArchiveReader({"path": str(tmp_path)})
    got = [r for p in reader.partitions() for b in reader.read(p) for r in b.to_pylist()]
    assert len(got) == 40 and all(r["error"] is None for r in got) and len(calls) == 80
    assert isinstance(pafs.LocalFileSystem(), pafs.FileSystem)
