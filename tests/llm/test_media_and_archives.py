"""Audio columns and WARC archives."""

import base64
import hashlib
import zlib

import numpy as np
import pytest

from binsketch.llm import audio, warc
from binsketch.llm.common import fresh_path


def test_tables_have_the_known_ends():
    mu, a = audio.TABLES["mulaw"], audio.TABLES["alaw"]
    assert (mu[0], mu[0x7F], mu[0x80], mu[0xFF]) == (-32124, 0, 32124, 0)
    assert (a[0x55], a[0xD5], a[0x2A], a[0xAA]) == (-8, 8, -32256, 32256)
    assert len(set(mu.tolist())) == 255 and len(set(a.tolist())) == 256


def slow_adpcm(block):
    value, index = int.from_bytes(block[:2], "little", signed=True), min(block[2], 88)
    out = [value]
    for byte in block[4:]:
        for code in (byte & 15, byte >> 4):
            step = int(audio.STEPS[index])
            change = (step >> 3) + (step >> 2) * (code & 1) + (step >> 1) * (code >> 1 & 1) + step * (code >> 2 & 1)
            value = max(-32768, min(32767, value - change if code & 8 else value + change))
            index = max(0, min(88, index + int(audio.MOVES[code & 7])))
            out.append(value)
    return out


def test_adpcm_equals_a_plain_decoder():
    data = np.random.default_rng(3).integers(0, 256, 64 * 20).astype(np.uint8)
    got = audio.adpcm_decode(data)
    assert [r.tolist() for r in got] == [slow_adpcm(data[i : i + 64].tobytes()) for i in range(0, len(data), 64)]


def test_resampling():
    pcm = np.array([0, 100, -100], np.int16)
    assert audio.resampled(pcm, 2, 1).tolist() == [0, 50, 100, 0, -100, -100]
    assert audio.resampled(pcm, 1, 1).tolist() == pcm.tolist()
    assert audio.resampled(pcm, 1, 2).tolist() == [0, -100]
    assert audio.resampled(pcm[:0], 2, 1).tolist() == []


@pytest.mark.parametrize("codec", ["mulaw", "alaw", "adpcm", None])
def test_payloads_come_back(edge, nothing, codec):
    media = audio.stored(edge, codec)
    got = {r.doc_id: r for r in audio.media_digests(media).collect()}
    for r in edge.collect():
        raw = (r.text or "").encode()
        payload = raw + b"\0" * (max(64, -(-len(raw) // 64) * 64) - len(raw))
        g = got[r.doc_id]
        assert (g.n_bytes, g.payload_bytes, g.payload_sha256, g.tail_crc32) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
    assert got[5].feature == got[6].feature and got[5].media_sha256 == got[6].media_sha256
    assert audio.media_digests(audio.stored(nothing, codec)).count() == 0
    pcm = {r.doc_id: r for r in audio.decoded(media).collect()}
    assert all(r.error is None and len(r.pcm) == 2 * r.n_samples for r in pcm.values())
    both = audio.media_digests(media, with_pcm=True).collect()
    assert all(bytes(r.pcm) == bytes(pcm[r.doc_id].pcm) for r in both)
    assert {r.codec for r in both} == ({codec} if codec else set(audio.TAGS))


def test_long_audio_in_parts():
    pcm = np.random.default_rng(2).integers(-32768, 32768, 10_000).astype(np.int16)
    for up, down in ((2, 1), (3, 7), (147, 80)):
        assert (audio.resampled(pcm, up, down, 999) == audio.resampled(pcm, up, down)).all()
    assert audio.features(pcm, 777) == audio.features(pcm)


def test_foreign_media_is_told(spark):
    rows = spark.createDataFrame([(1, None), (2, bytearray(b"RIFF....")), (3, bytearray(audio.container(b"\xff" * 64, "mulaw")))], "doc_id long, media binary")
    got = {r.doc_id: r for r in audio.decoded(rows).collect()}
    assert got[1].error and got[2].error and got[1].pcm is None and got[3].error is None


def pages(spark):
    rows = [(1, "http://a.example/x", "<p>one</p>"), (2, None, "<p>one</p>"), (3, "http://b.example/", None), (4, "odd url\nX: y", ""), (5, "http://c.example", "é" * 100_000), (7, "http://a.example/x", "<p>one</p>")]
    return spark.createDataFrame([(*r, "clash", "clash") for r in rows], "page_id long, url string, html string, hex string, first string")


def test_archives(spark):
    df = pages(spark)
    got = {r.page_id: r for r in warc.archive_digests(df).collect()}
    html = {r.page_id: (r.html or "").encode() for r in df.collect()}
    assert set(got) == set(html)
    for p, h in html.items():
        top = max(q for q, x in html.items() if x == h)
        g = got[p]
        assert (g.payload_bytes, g.payload_digest) == (len(h), base64.b32encode(hashlib.sha1(h).digest()).decode())
        assert (g.record_type, g.refers_to) == (("response", None) if p == top else ("revisit", top))
    assert warc.archive_digests(df.limit(0)).count() == 0


def test_captures_are_nested(spark):
    folder = fresh_path(spark, "warc-test")
    warc.write_warc(pages(spark), folder, file_bytes=200)
    files = spark.read.format("binaryFile").load(f"{folder}/part-*.warc.gz")
    rows = warc.captures(warc.read_warc(files, with_payload=True)).collect()
    assert len(rows) == 6 and files.count() > 1
    for r in rows:
        assert r.request.record_type == "request" and r.metadata.page_id == r.page_id
        assert (r.response.payload is None) == (r.response.record_type == "revisit")
    alone = warc.captures(warc.read_warc(files).filter("record_type = 'request'")).collect()
    assert all(r.response is None and r.page_id is None for r in alone)


def test_damage_is_seen():
    with pytest.raises(ValueError):
        list(warc.members(warc.record("request", "<x>", b"abc", {})[:-4]))
    with pytest.raises(ValueError):
        warc.parsed(b"no record")


def test_stored_media_is_read_back(spark, sf):
    from binsketch.llm import queries

    got = queries.op7_telephony_audio(spark, sf)
    assert got.inputFiles() and all("/media-" in f for f in got.inputFiles())
    flight = audio.media_digests(audio.stored(spark.read.parquet(f"{sf}/documents.parquet")))
    got = {r.doc_id: r for r in got.collect()}
    assert {r.codec for r in got.values()} == set(audio.TAGS)
    for r in flight.collect():
        assert got[r.doc_id][: len(r)] == tuple(r)
        assert audio.features(np.frombuffer(got[r.doc_id].pcm, "<i2")) == r.feature


def test_pages_without_id_and_repeated_pages(spark):
    rows = [(1, "http://a.example/", "<p>one</p>")] * 3 + [(None, "http://b.example/", "<p>two</p>")] * 2 + [(None, None, "<p>one</p>"), (3, "http://c.example/", None), (2, "u", "")]
    got = warc.archive_digests(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert sorted(((r.page_id, r.record_type, r.refers_to, r.payload_bytes) for r in got), key=str) == sorted([(1, "response", None, 10), (1, "revisit", 1, 10), (1, "revisit", 1, 10), (None, "response", None, 10), (None, "revisit", None, 10), (None, "revisit", 1, 10), (3, "response", None, 0), (2, "revisit", 3, 0)], key=str)
    assert "without a page_id" in warc.archive_digests.__doc__ and "equal" in warc.archive_digests.__doc__


def test_leftovers_of_lost_attempts_are_not_read(spark):
    from binsketch.llm.common import shared_dir

    folder = f"{shared_dir(spark)}/warc-leftovers"
    warc.put(folder, "part-000000-99-0000.warc.gz", warc.capture(77, "http://x/", b"lost", "00", None))
    warc.put(folder, "part-000001-99-0000.warc.gz", b"half a rec")
    got = warc.archive_digests(pages(spark), folder).collect()
    assert sorted(r.page_id for r in got) == [1, 2, 3, 4, 5, 7]


def test_members_across_chunks(monkeypatch):
    monkeypatch.setattr(warc, "STEP", 7)
    blob = b"".join(warc.record("resource", f"<{i}>", bytes([i]) * 50, {}) for i in range(5))
    assert [warc.parsed(m)[1] for m in warc.members(blob)] == [bytes([i]) * 50 for i in range(5)]
