import hashlib
import random
from collections import Counter

import numpy as np
import pytest

from fuzzcount.llm import repeat_spans as spans
from fuzzcount.llm.warc import read_archive, read_archives, round_trip, write_archives

LENGTH = spans.LENGTH


def brute(texts):
    seen = Counter(t[i : i + LENGTH] for t in texts for i in range(len(t) - LENGTH + 1))
    out = []
    for t in texts:
        gone = np.zeros(len(t), bool)
        for i in range(len(t) - LENGTH + 1):
            if seen[t[i : i + LENGTH]] > 1:
                gone[i : i + LENGTH] = True
        runs = int((np.diff(np.r_[0, gone.astype(int)]) == 1).sum())
        out.append((len(t), int(gone.sum()), runs, hashlib.sha256(bytes(b for b, g in zip(t, gone, strict=True) if not g)).hexdigest()))
    return out


def test_marks_equal_brute_force():
    rng = random.Random(2)
    for _ in range(150):
        length, letters = rng.choice([1, 3, 8]), rng.choice([b"ab", b"abcdef"])
        texts = [bytes(rng.choice(letters) for _ in range(rng.randint(1, 60))) for _ in range(rng.randint(1, 6))]
        seen = Counter(t[i : i + length] for t in texts for i in range(len(t) - length + 1))
        want = [[i for i in range(len(t) - length + 1) if seen[t[i : i + length]] > 1] for t in texts]
        assert [[i for a, b in found for i in range(a, b)] for found in spans.repeated_starts(texts, length)] == want


@pytest.mark.parametrize("bin_bytes", [4 << 20, 6000, 100])
def test_removed_bytes_equal_brute_force(spark, monkeypatch, bin_bytes):
    monkeypatch.setattr(spans, "BIN_BYTES", bin_bytes)
    rng = random.Random(3)
    letters = "abcdefghij "
    make = lambda n: "".join(rng.choice(letters) for _ in range(n))
    passage, texts = make(700), []
    for i in range(14):
        at = rng.randint(0, 300)
        texts.append(make(rng.randint(0, 500)) + passage[at : at + rng.randint(380, 700)] + make(rng.randint(0, 500)))
    texts += ["é" * 500, "Ther " * 400, texts[0], texts[0], make(399), "", make(50) + "x" * 900 + make(50)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    got = {r["doc_id"]: tuple(r)[1:] for r in spans.removed(docs).collect()}
    assert [got[i] for i in range(len(texts))] == brute([t.encode() for t in texts])


def test_odd_rows(odd_docs, no_docs):
    found = spans.removed(odd_docs).toPandas().set_index("doc_id")
    assert len(found) == 11 and found.loc[4].n_removed == found.loc[4].n_bytes and found.loc[9].n_removed == 1500 and found.loc[1].n_bytes == 0
    assert spans.removed(no_docs).count() == 0


PAGES = "page_id bigint, url string, html string, extra int"


def test_round_trip_of_odd_pages(spark):
    same = "é" * 80
    rows = [(3, "http://a/\r\nx", same, 1), (1, None, same, 1), (2, "u", "short", 1), (4, "u", "short", 1), (5, "u", None, 1), (None, "u", same, 1), (1, None, same, 1)]
    found = round_trip(spark.createDataFrame(rows, PAGES)).toPandas()
    assert len(found) == 7
    by = found.dropna(subset=["page_id"]).groupby("page_id").first()
    assert by.loc[3].record_type == "revisit" and by.loc[3].refers_to == 1 and by.loc[1].record_type == "response" and by.loc[3].payload_bytes == 160
    assert by.loc[4].record_type == "response" and by.loc[5].payload_digest == hashlib.sha256(b"").hexdigest()
    assert round_trip(spark.createDataFrame([], PAGES)).count() == 0


def test_archives_roll_and_damage_is_told(spark, tmp_path):
    pages = spark.createDataFrame([(i, "u", "".join(random.Random(i).choices("abcdef", k=3000)), 0) for i in range(60)], PAGES).repartition(2)
    manifest = write_archives(pages, str(tmp_path / "w"), roll_bytes=20_000)
    files = [r["path"] for r in manifest.collect()]
    assert len(files) > 2 and read_archives(manifest).count() == 60
    data = bytearray(open(files[0], "rb").read())
    with open(files[0], "wb") as file:
        file.write(data[: len(data) // 2])
    with pytest.raises(ValueError, match="cut off|differs"):
        list(read_archive(files[0]))


def test_long_records_are_read_in_pieces(tmp_path, monkeypatch):
    """Members longer than a piece, payloads that look like ends of records, and wrong lengths."""
    import gzip

    from fuzzcount.llm import warc

    monkeypatch.setattr(warc, "CHUNK", 97)
    payloads = [random.Random(i).randbytes(5000) + b"\r\n\r\n" * 3 for i in range(4)] + [b"", b"x"]
    records = [warc.record(i, "http://u/", p, None) for i, p in enumerate(payloads)]
    path = tmp_path / "a.warc.gz"
    path.write_bytes(b"".join(r if r[:2] == b"\x1f\x8b" else gzip.compress(r) for r in records))
    found = list(warc.read_archive(str(path)))
    assert [f["payload"] for f in found] == payloads and [f["at"] for f in found] == list(range(6))
    assert [f["payload"] for f in warc.read_archive(str(path), keep_payload=False)] == [None] * 6
    plain = records[0] if records[0][:5] == b"WARC/" else gzip.decompress(records[0])
    for broken in (plain[:-4], plain + b"more", plain.replace(b"WARC/1.1", b"nothing", 1), plain.replace(payloads[0][:9], b"123456789", 1)):
        with pytest.raises(ValueError):
            warc.parse_record(iter([broken[i : i + 50] for i in range(0, len(broken), 50)]))


def test_crowded_bins_equal_brute_force(spark, monkeypatch):
    """Many distinct texts around one passage meet in one bin, which is split by the next least hashes and then counted."""
    rng = random.Random(5)
    make = lambda n: "".join(rng.choice("abcdefgh ") for _ in range(n))
    passage = make(380)
    texts = [make(rng.randint(30, 200)) + passage + make(30) for _ in range(60)]
    texts += [t[5:-5] for t in texts[:8]] + [t[:200] + "Z" + t[200:] for t in texts[:8]]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    for limit in (1 << 20, 8000, 900):
        monkeypatch.setattr(spans, "BIN_BYTES", limit)
        got = {r["doc_id"]: tuple(r)[1:] for r in spans.removed(docs).collect()}
        assert [got[i] for i in range(len(texts))] == brute([t.encode() for t in texts])


def test_given_documents_equal_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    rows = sorted((r["doc_id"], (r["text"] or "").encode()) for r in docs.collect())
    seen = Counter(hash(t[i : i + LENGTH]) for _, t in rows for i in range(len(t) - LENGTH + 1))
    want = {}
    for i, t in rows:
        gone = np.zeros(len(t) + 1, bool)
        for at in range(len(t) - LENGTH + 1):
            if seen[hash(t[at : at + LENGTH])] > 1:
                gone[at : at + LENGTH] = True
        want[i] = (len(t), int(gone.sum()), int((np.diff(np.r_[0, gone.astype(int)]) == 1).sum()))
    assert {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"]) for r in spans.removed(docs).collect()} == want
