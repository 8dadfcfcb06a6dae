import gzip
import hashlib
import io

import pytest
from memojoin.llm import warc


def make(n=6, compressed=True):
    out, at = b"", []
    for k in range(n):
        payload = (b"<p>%d</p>" % k) * 40
        data = warc.record(k, f"http://x/{k}", payload, hashlib.sha256(payload).hexdigest())
        at.append(len(out))
        out += gzip.compress(data) if compressed else data
    return out, [*at, len(out)]


@pytest.mark.parametrize("compressed", [True, False])
def test_damage_is_quarantined_and_later_records_recovered(compressed):
    data, at = make(compressed=compressed)
    name = "a.warc.gz" if compressed else "a.warc"
    whole = list(warc.salvage_range(io.BytesIO(data), name, 0, len(data)))
    assert [r["page_id"] for r in whole] == list(range(6))
    bad = bytearray(data)
    middle = at[3] - (12 if compressed else 30)  # within the payload, or the compressed data
    bad[middle] ^= 0xFF
    got = list(warc.salvage_range(io.BytesIO(bytes(bad)), name, 0, len(bad)))
    assert [r["page_id"] for r in got if r["kind"] == "record"] == [0, 1, 3, 4, 5]
    gap = [r for r in got if r["kind"] == "gap"]
    assert [(g["offset"], g["length"]) for g in gap] == [(at[2], at[3] - at[2])]
    cut = list(warc.salvage_range(io.BytesIO(data[: at[5] + 20]), name, 0, at[5] + 20))
    assert [r["page_id"] for r in cut if r["kind"] == "record"] == [0, 1, 2, 3, 4]
    assert cut[-1]["kind"] == "gap" and cut[-1]["offset"] == at[5]


@pytest.mark.parametrize("compressed", [True, False])
@pytest.mark.parametrize("step", [50, 333, 1000])
def test_ranges_own_each_record_once(compressed, step):
    data, _ = make(20, compressed)
    name = "a.warc.gz" if compressed else "a.warc"
    got = [r["page_id"] for s in range(0, len(data), step) for r in warc.salvage_range(io.BytesIO(data), name, s, s + step) if r["kind"] == "record"]
    assert got == list(range(20))


def test_edges_and_extra_columns(spark):
    rows = [(1, "u", "x" * 200, 1), (2, None, "x" * 200, 1), (None, "u\r\n", "x" * 200, 1), (3, "u", None, 1), (4, "u", "short", 1), (5, "u", "short", 1), (1, "u", "x" * 200, 1)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, digest int")
    for compressed in (True, False):
        folder = warc.scratch(spark, "t")
        m = warc.write(warc.with_roles(pages), folder, compressed)
        got = warc.salvage(m, folder).where("kind='record'").select("page_id", "record_type", "refers_to", "payload_bytes").collect()
        want = [(1, "response", None, 200), (1, "response", None, 200), (2, "revisit", 1, 200), (None, "revisit", 1, 200), (3, "response", None, 0), (4, "response", None, 5), (5, "response", None, 5)]
        assert sorted(map(repr, map(tuple, got))) == sorted(map(repr, want))
    folder = warc.scratch(spark, "t")
    assert warc.salvage(warc.write(warc.with_roles(pages.limit(0)), folder), folder).count() == 0


@pytest.mark.parametrize("compressed", [True, False])
@pytest.mark.parametrize("step", [100, 333, 1000, 1 << 20])
def test_gaps_across_ranges_are_logged_whole(spark, tmp_path, compressed, step):
    data, at = make(20, compressed)
    bad = bytearray(data)
    for k in (0, 3, 4, 5, 6, 11, 18, 19):
        bad[at[k + 1] - (12 if compressed else 30)] ^= 0xFF
    path = str(tmp_path / ("a.warc" + ".gz" * compressed))
    with open(path, "wb") as f:
        f.write(bad)
    manifest = spark.createDataFrame([(path, len(bad), 20)], warc.MANIFEST)
    got = warc.salvage(manifest, f"file://{tmp_path}", range_bytes=step)
    assert sorted(r["page_id"] for r in got.where("kind = 'record'").collect()) == [1, 2, 7, 8, 9, 10, 12, 13, 14, 15, 16, 17]
    want = [(at[a], at[b] - at[a]) for a, b in ((0, 1), (3, 7), (11, 12), (18, 20))]
    gaps = got.where("kind = 'gap'").collect()
    assert sorted((r["offset"], r["length"]) for r in gaps) == want and all(r["reason"] for r in gaps)


def test_a_damaged_length_is_not_read():
    data, at = make(30, compressed=False)
    for length in (b"9" * 12, b"7"):
        start = data.index(b"Content-Length: ", at[3]) + 16
        bad = data[:start] + length + data[data.index(b"\r\n", start) :]
        read = []

        class Counted(io.BytesIO):
            def read(self, n=-1):
                got = super().read(n)
                read.append(len(got))
                return got

        got = list(warc.salvage_range(Counted(bad), "a.warc", 0, len(bad)))
        assert [r["page_id"] for r in got if r["kind"] == "record"] == [k for k in range(30) if k != 3]
        assert [r["offset"] for r in got if r["kind"] == "gap"] == [at[3]]
        assert sum(read) <= 2 * len(bad) + 100 * 30
