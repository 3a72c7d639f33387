import random
import zlib
from collections import Counter, deque

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

from fuzzcount.llm.packing import Shard, pack
from fuzzcount.llm.prefix_counts import PrefixCounter, prefix_table, token_counts
from fuzzcount.llm.queries import packed

WORDS = public_tokenizers.path("word_bpe_49k.json")
ODD = "ab'sΣİé\u0301 \t\x1c\x1d\x85\u200b'rellve<|endoftext|>!!?中文1²٣😀A \x00ﬁ\u2028"


def test_every_prefix_is_exact():
    counter, library, rng = PrefixCounter(WORDS), Tokenizer.from_file(WORDS), random.Random(4)
    count = lambda t: len(library.encode(t, add_special_tokens=False).ids)
    for _ in range(400):
        text = "".join(rng.choice(ODD) for _ in range(rng.randint(0, 25)))
        ends = counter.word_ends(text + "<|endoftext|>" + text)
        assert ends[-1] == count(text + "<|endoftext|>" + text)
        if "<|" not in text:
            normal, counts = counter.every_prefix(text)
            assert [int(c) for c in counts] == [count(normal[:i]) for i in range(len(normal) + 1)]
            assert count(counter.fits(text, 3)) <= 3


def test_counts_of_odd_rows(odd_docs, no_docs):
    library = Tokenizer.from_file(WORDS)
    found = {r["doc_id"]: r for r in token_counts(odd_docs, WORDS).collect()}
    texts = {r["doc_id"]: r["text"] or "" for r in odd_docs.collect()}
    assert all(found[i]["n_tokens"] == len(library.encode(t, add_special_tokens=False).ids) and found[i]["n_bytes"] == len(t.encode()) for i, t in texts.items())
    assert token_counts(no_docs, WORDS).count() == 0
    assert prefix_table(odd_docs.where("doc_id = 2"), WORDS).first()["prefix_tokens"] == [0]


def check_pieces(docs, pieces):
    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    want = {i: np.array([*library.encode(t or "", add_special_tokens=False).ids, 1], "<u4") for i, t in docs}
    for doc_id, own in pieces.groupby("doc_id"):
        at = 0
        for p in own.sort_values("start").itertuples():
            assert p.start == at and p.doc_tokens == len(want[doc_id]) and p.ids_crc32 == zlib.crc32(want[doc_id][at : at + p.length].tobytes())
            at += p.length
        assert at == len(want[doc_id])
    assert set(pieces["doc_id"]) == set(want)
    for _, row in pieces.groupby("sequence_id"):
        row = row.sort_values("offset")
        assert list(row["offset"]) == [0, *row["length"].cumsum()[:-1]]
        size = row["length"].sum()
        assert size <= 2048 and size & (size - 1) == 0


def test_packing_is_whole(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    check_pieces([(r["doc_id"], r["text"]) for r in docs.collect()], packed(docs).toPandas())


def test_packing_of_odd_rows(odd_docs, no_docs):
    few = odd_docs.where("doc_id IS NOT NULL").dropDuplicates(["doc_id"])
    check_pieces([(r["doc_id"], r["text"]) for r in few.collect()], packed(few).toPandas())
    assert packed(no_docs).count() == 0 and packed(odd_docs).count() >= 11


def test_windows_keep_the_mixture(spark):
    rows = [(i, "word " * 900, "big" if i % 4 else "small") for i in range(80)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, source string")
    pieces = pack(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN).toPandas()
    full = pieces.groupby("sequence_id").filter(lambda g: g["length"].sum() == 2048)
    share = full[full.source == "small"].groupby("sequence_id")["length"].sum() / 2048
    assert share.reindex(full["sequence_id"].unique(), fill_value=0).sub(0.25).abs().max() <= 0.15


def test_windows_keep_the_mixture_of_many_sources(spark):
    rows = [(i, "word " * 900, f"s{i % 20}") for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, source string")
    pieces = pack(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN).toPandas()
    full = pieces.groupby("sequence_id").filter(lambda g: g["length"].sum() == 2048)
    share = full.pivot_table(index="sequence_id", columns="source", values="length", aggfunc="sum", fill_value=0) / 2048
    off = share.sub(1 / 20).abs().sum(axis=1) / 2
    assert share.shape[1] == 20 and (share > 0).all().all() and off.max() <= 0.05


def test_windows_keep_uneven_shares_and_deficits():
    shares = {"big": 1 / 3} | {f"s{i:02}": 2 / 57 for i in range(19)}
    shard = Shard(dict(shares), {"big": -30_000.0, "s00": 30_000.0})
    left = {s: int(2_000_000 * p) for s, p in shares.items()}
    windows, whole = {}, dict.fromkeys(shares, 0)
    for s, _, _, n, number, _ in shard.pack({s: deque([(0, n)]) for s, n in left.items()}, dict(left)):
        windows.setdefault(number, dict.fromkeys(shares, 0))[s] += n
        whole[s] += n
    assert whole == left
    off = [sum(abs(w[s] / 2048 - p) for s, p in shares.items()) / 2 for w in list(windows.values())[:800]]
    assert max(off) <= 0.15, max(off)


def test_windows_of_thousands_of_sources_have_no_slivers():
    shares = {f"s{i:04}": 1 / 5000 for i in range(5000)}
    pieces = list(Shard(shares, {}).pack({s: deque([(0, 160)]) for s in shares}, dict.fromkeys(shares, 160)))
    assert sum(p[3] for p in pieces) == 800_000 and len(pieces) <= 800_000 / 16 * 1.1
    early = Counter()
    for s, _, _, n, number, _ in pieces:
        early[s] += n if number < 195 else 0
    assert max(early.values()) - min(early[s] for s in shares) <= 32


def test_targets_hold_with_thousands_of_sources(spark):
    rows = [(i, "word " * 600, "big") for i in range(100)] + [(1000 + i, "word " * 12, f"s{i}") for i in range(5000)] + [(9000 + i, "word " * 600, None) for i in range(100)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, source string")
    pieces = pack(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, targets={"big": 0.75, None: 0.25}).toPandas()
    assert pieces["length"].sum() == pieces.groupby("doc_id")["doc_tokens"].first().sum() and pieces["source"].nunique() == 5001
    for _, window in sorted(pieces.groupby("sequence_id"))[:25]:
        assert abs(window.loc[window["source"] == "big", "length"].sum() / 2048 - 0.75) <= 0.01
        assert abs(window.loc[window["source"].isna(), "length"].sum() / 2048 - 0.25) <= 0.01
