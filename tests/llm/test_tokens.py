import random
import zlib
from pathlib import Path

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from tokenizers import Tokenizer

from codedreg.llm import bpe, packing, shards, wordtable
from codedreg.llm.tokens import file_coder

RANKS, FILE = P.path("byte_bpe_50k.tiktoken"), P.path("byte_bpe_50k.json")
TEXTS = [
    "", "a", " ", "  ", "\n", "word", " word", "two  spaces", "tab\tand\nline\n\n end ", "don't I'll we've", "naïve façade — “quoted” 123 4567",
    "ſ İ ß Ǆ   x y　z \x1c\x85\xa0", "日本語のテキスト 😀😀 é", "x" * 5000, "<|endoftext|> <|im_start|>", "a,b;c. d! e? f:", "\r\n mixed \r\n",
]


def random_texts(n=400):
    draw = random.Random(3)
    pools = [range(0x20, 0x7F), range(0, 0x250), range(0x300, 0x3100), range(0x1F300, 0x1F700), [0x20, 0x0A, 0x0D, 0x09, 0x85, 0xA0, 0x3000, 0x1C]]
    return ["".join(chr(draw.choice(draw.choice(pools))) for _ in range(draw.randrange(60))) for _ in range(n)]


def test_ids_are_those_of_the_rank_library():
    own = bpe.Coder(bpe.read_ranks(RANKS), P.PATTERN)
    ranks = {t: i for i, t in enumerate(bpe.read_ranks(RANKS))}
    library = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    texts = TEXTS + random_texts()
    for text, ids in zip(texts, own.encode_many(texts)):
        assert list(memoryview(ids).cast("I")) == library.encode_ordinary(text), ascii(text)
        assert own.decode(ids) == text.encode()


def test_small_tables_change_nothing(monkeypatch):
    texts = (TEXTS + random_texts(100)) * 2
    large = list(bpe.Coder(bpe.read_ranks(RANKS), P.PATTERN).encode_many(texts))
    monkeypatch.setattr(bpe, "CACHE_ENTRIES", 20)
    monkeypatch.setattr(bpe, "GROUP_CHARS", 50)
    small = bpe.Coder(bpe.read_ranks(RANKS), P.PATTERN)
    small.words = wordtable.WordTable(small.learn_words, 64)
    assert list(small.encode_many(texts)) == large


def test_equal_hashes_do_not_mix_words(monkeypatch):
    """Every second word gets the hash of another one."""
    texts = [x for x in TEXTS + random_texts(60) if len(x) < 1000]
    plain = bpe.Coder(bpe.read_ranks(RANKS), P.PATTERN)
    right = list(plain.encode_many(texts))
    hashes = wordtable.WordTable.hashes
    monkeypatch.setattr(wordtable.WordTable, "hashes", lambda *a: hashes(*a) % wordtable.np.uint64(7) + wordtable.np.uint64(1))
    odd = bpe.Coder(bpe.read_ranks(RANKS), P.PATTERN)
    assert list(odd.encode_many(texts)) == right and [odd.encode(x) for x in texts] == right


def test_ids_are_those_of_the_tokenizer_file():
    library = Tokenizer.from_file(FILE)
    library.encode_special_tokens = True
    texts = TEXTS + random_texts(200)
    own = file_coder(FILE, P.PATTERN)
    assert isinstance(own, bpe.Coder)
    for text, ids in zip(texts, own.encode_many(texts)):
        assert list(memoryview(ids).cast("I")) == library.encode(text, add_special_tokens=False).ids


def test_other_files_go_to_the_library():
    path = P.path("word_bpe_49k.json")
    own, library = file_coder(path, P.PATTERN), Tokenizer.from_file(path)
    assert list(memoryview(own.encode("Some words here")).cast("I")) == library.encode("Some words here", add_special_tokens=False).ids


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "x") for i, t in enumerate(TEXTS)] + [(100, None, "x"), (None, "no id", None), (3, "word", "y"), (200, "many words " * 4000, "x")]
    rows += [(300 + i, f"text {i} " * (i % 97), "z") for i in range(300)]
    return spark.createDataFrame(rows, "doc_id long, text string, n_tokens string").repartition(5)


def test_encode_documents(spark, docs):
    rows = bpe.encode_documents(docs, RANKS, P.PATTERN).collect()
    assert len(rows) == docs.count()
    by = {r["doc_id"]: r for r in rows}
    assert by[100]["n_tokens"] == 0 and by[100]["decoded"] == b"" and bytes(by[14]["decoded"]).decode() == TEXTS[14]
    assert bpe.encode_documents(docs.limit(0), RANKS, P.PATTERN).count() == 0


@pytest.mark.parametrize("n", [1, 15, 16, 17, 100, 682, 683, 1000, 1024, 1025, 2047, 2048, 2049, 100_000])
def test_cuts_fill_their_class(n):
    parts = packing.cut_lengths(n)
    assert sum(p for p, _ in parts) == n
    assert all(packing.CAPACITY // (k + 1) < p <= packing.CAPACITY // k and k * p >= (1 - packing.SLACK) * packing.CAPACITY for p, k in parts)


def test_packing(spark, docs):
    found = packing.pack_documents(docs, FILE, P.PATTERN).toPandas()
    own = file_coder(FILE, P.PATTERN)
    wanted = sorted((r["doc_id"] if r["doc_id"] is not None else -1, own.encode(r["text"] or "") + b"\x01\0\0\0") for r in docs.collect())
    pieces = found.fillna({"doc_id": -1}).sort_values(["doc_id", "start"])
    assert pieces["length"].sum() == sum(len(ids) // 4 for _, ids in wanted)
    by = {d: ids for d, ids in wanted if d != 3}
    for r in pieces[pieces["doc_id"] != 3].itertuples():
        ids = by[int(r.doc_id)]
        assert r.doc_tokens == len(ids) // 4 and r.ids_crc32 == zlib.crc32(ids[4 * r.start : 4 * (r.start + r.length)])
    total = found.groupby("sequence_id")["length"].sum()
    assert total.max() <= packing.CAPACITY and (packing.CAPACITY - total).sum() <= 0.04 * total.sum() + packing.CAPACITY
    ordered = found.sort_values(["sequence_id", "offset"])
    assert (ordered.groupby("sequence_id")["length"].cumsum() - ordered["length"] == ordered["offset"]).all()
    assert packing.pack_documents(docs.limit(0), FILE, P.PATTERN).count() == 0


def test_many_workers_leave_little_open(spark):
    rows = spark.range(3000).selectExpr("id as doc_id", "repeat('some words ', cast(id % 53 as int)) as text").repartition(90)
    found = packing.pack_documents(rows, FILE, P.PATTERN).toPandas()
    total = found.groupby("sequence_id")["length"].sum()
    assert (packing.CAPACITY - total).sum() <= 0.03 * total.sum() + packing.CAPACITY


@pytest.mark.parametrize("n", [1, 2, 5, 64, 1000])
def test_permutation(n):
    assert sorted(shards.permute(i, n, 99) for i in range(n)) == list(range(n))


def streams(docs, own):
    """The ids of all documents with their end ids, by document."""
    return {r["doc_id"]: list(memoryview(own.encode(r["text"] or "")).cast("I")) + [shards.END_ID] for r in docs.collect() if r["doc_id"] != 3}


def test_slots_are_the_permutation(spark, docs):
    for n in (1, 5, 64, 683):
        assert shards.slots_of(np.arange(n), n).tolist() == [shards.permute(i, n, shards.KEY) for i in range(n)]
    order = shards.Order(docs, FILE, P.PATTERN, 64)
    assert sorted(r["slot"] for r in order.sequences().collect()) == list(range(order.total))


def test_packed_ids():
    draw = np.random.default_rng(1)
    for ids in (np.zeros(0, "<u2"), draw.integers(0, 1 << 16, 200_000).astype("<u2"), draw.geometric(0.01, 5000).astype("<u2"), draw.integers(0, 1 << 20, 500).astype("<u4")):
        assert (shards.unpack_ids(shards.pack_ids(ids), len(ids), ids.itemsize) == ids).all()


def test_shards_round_trip(spark, docs, tmp_path):
    path, stride, slots = str(tmp_path / "s"), 64, 50
    listed = shards.materialise(docs, FILE, P.PATTERN, stride, slots, path).toPandas()
    files, size = shards.shard_files(spark, path), shards.record_bytes(stride, 2)
    n = listed["slot"].nunique()
    assert sorted(listed["slot"].unique()) == list(range(n)) and sorted(files) == list(range(-(-n // slots)))
    raw = {s: Path(f.removeprefix("file:")).read_bytes() for s, f in files.items()}
    assert all(len(b) == size * min(slots, n - slots * s) for s, b in raw.items())
    wanted = streams(docs, file_coder(FILE, P.PATTERN))
    got = {}
    for r in listed.itertuples():
        record = raw[r.shard][r.byte_offset : r.byte_offset + size]
        slot, ids = shards.parse(record, 2)
        assert r.byte_offset == r.slot % slots * size and slot == r.slot and len(ids) == r.n_tokens and zlib.crc32(record) == r.record_crc32
        if r.doc_id == r.doc_id and r.doc_id != 3:
            got.setdefault(int(r.doc_id), []).append((r.start, ids[r.offset : r.offset + r.length]))
    for doc, ids in wanted.items():
        if doc is not None:
            pieces = sorted(got[doc])
            assert [x for _, p in pieces for x in p] == ids and [s for s, _ in pieces] == [sum(len(p) for _, p in pieces[:i]) for i in range(len(pieces))]
    assert listed["length"].sum() == sum(len(file_coder(FILE, P.PATTERN).encode(r["text"] or "")) // 4 + 1 for r in docs.collect())


def test_readers_resume_at_any_slot(spark, docs, tmp_path):
    path, stride, slots = str(tmp_path / "s"), 64, 50
    order = shards.Order(docs, FILE, P.PATTERN, stride)
    shards.write_shards(order, path, slots)
    held = {r["slot"]: np.frombuffer(shards.pa.decompress(bytes(r["ids"]), 2 * r["n_tokens"], shards.CODEC), "<u2").tolist() for r in order.sequences().collect()}
    n = len(held)
    for start in (0, 1, 49, 50, 120, n - 1):
        later = {r["slot"]: list(r["ids"]) for r in shards.read_shards(spark, path, start, stride, slots).collect()}
        assert later == {s: x for s, x in held.items() if s >= start}
        assert shards.seek_slots(spark, shards.shard_files(spark, path), start, 1, stride, slots) == [(start, held[start])]
    assert [s for s, _ in shards.seek_slots(spark, shards.shard_files(spark, path), 60, 7, stride, slots)] == list(range(60, 67))


def test_shards_of_nothing(spark, docs, tmp_path):
    assert shards.materialise(docs.limit(0), FILE, P.PATTERN, 64, 50, str(tmp_path / "none")).count() == 0
    one = docs.where("doc_id = 100")
    assert [(r["length"], r["n_tokens"]) for r in shards.materialise(one, FILE, P.PATTERN, 64, 50, str(tmp_path / "one")).collect()] == [(1, 1)]


def test_query_lists_what_it_wrote(spark, sf_dir):
    from codedreg.llm import queries

    listed = queries.op7_training_order(spark, sf_dir).toPandas()
    assert listed["doc_id"].nunique() == spark.read.parquet(f"{sf_dir}/documents.parquet").count()
    assert (listed.groupby("slot")["length"].sum() == listed.groupby("slot")["n_tokens"].first()).all()
