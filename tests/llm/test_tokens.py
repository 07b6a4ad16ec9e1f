import hashlib
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from tests.llm import edge
from windowjoin.llm import bpe, edit_counts, packing, token_files
from windowjoin.llm.queries import three_edits, vocabulary
from windowjoin.llm.word_tokens import ChunkTokenizer

WORDS, BYTES = vocabulary("word_bpe_49k.json"), vocabulary("byte_bpe_50k.json")
ALPHABET = "ab '\n\t \x1c\x1d\x85  sdtmrel1²٣!?éß́漢字😀=_ ​\x00İΣ</w>WS"


def noise(n: int, seed: int) -> list[str]:
    rng = random.Random(seed)
    return ["".join(rng.choice(ALPHABET) for _ in range(rng.randrange(60))) for _ in range(n)]


def library(definition: str, texts: list) -> list[list[int]]:
    t = Tokenizer.from_str(definition)
    return [e.ids for e in t.encode_batch([x or "" for x in texts], add_special_tokens=False)]


def test_chunks_equal_library():
    texts = [t or "" for t in edge.texts()] + noise(3000, 1) + ["<|STARTOFTEXT|> H̱ ẖ", "<|startoftext|>x", "x" * 255 + "ab", "x" * 255 + "ba", "é" * 200 + "ab " + "é" * 200 + "ba"]
    tok = ChunkTokenizer(WORDS, most_chunks=500)  # begins anew often
    for k in range(0, len(texts), 400):
        part = texts[k : k + 400]
        ids, counts = tok.encode(pa.array(part))
        assert [list(x) for x in np.split(ids, np.cumsum(counts)[:-1])] == library(WORDS, part)
    assert tok.encode(pa.array([], pa.string()))[0].size == 0


def test_numpy_bpe_equals_library():
    texts = [t or "" for t in edge.texts()] + noise(3000, 2)
    model = bpe.NumpyBPE(BYTES, most_words=300)
    ids, counts, decimal = model.encode_batch(texts)
    want = library(BYTES, texts)
    assert decimal == [",".join(map(str, w)) for w in want] and counts.tolist() == [len(w) for w in want]
    assert model.decode_batch(ids, counts) == texts


def test_one_pair_a_round_gives_the_same():
    model = bpe.NumpyBPE(BYTES)
    words = [w.encode() for w in noise(300, 3)] + [b"a" * 50]
    a = model.merge(words)
    model.together = False
    b = model.merge(words)
    assert (a[0] == b[0]).all() and (a[1] == b[1]).all()


@pytest.mark.parametrize("make", [edge.table, edge.with_repeats, edge.empty])
def test_bpe_round_trip(spark, make):
    docs = make(spark)
    rows = docs.select("doc_id", "text").collect()
    want = sorted((r.doc_id, len(i), hashlib.sha256(",".join(map(str, i)).encode()).hexdigest(), hashlib.sha256((r.text or "").encode()).hexdigest()) for r, i in zip(rows, library(BYTES, [r.text for r in rows]))) if rows and all(r.doc_id is not None for r in rows) else None
    got = bpe.round_trip_digests(docs, BYTES).collect()
    assert len(got) == len(rows)
    if want is not None:
        assert sorted(map(tuple, got)) == want
    back = bpe.decode(bpe.encode(docs, BYTES), BYTES).collect()
    assert sorted(map(repr, ((r.doc_id, r.text) for r in back))) == sorted(map(repr, ((r.doc_id, r.text or "") for r in rows)))


def crc(ids: list[int]) -> int:
    return zlib.crc32(np.array(ids, "<u4").tobytes())


@pytest.mark.parametrize("make", [edge.table, edge.empty])
def test_token_files(spark, make):
    docs = make(spark)
    rows = sorted((r.doc_id, r.text) for r in docs.collect())
    ids = [x + [1] for x in library(WORDS, [t for _, t in rows])] if rows else []
    starts = np.concatenate(([0], np.cumsum([len(x) for x in ids]))).astype(int)
    want = [(d, int(s), len(i), crc(i)) for (d, _), s, i in zip(rows, starts, ids)]
    assert sorted(map(tuple, token_files.token_file_table(docs, WORDS).collect())) == want


def test_token_files_layout(spark, tmp_path):
    import pyarrow.parquet as pq

    token_files.write_token_files(edge.with_repeats(spark), str(tmp_path / "t"), WORDS, files=3)
    parts = sorted((tmp_path / "t").glob("*.parquet"))
    last = None
    for p in parts:
        meta = pq.ParquetFile(p).metadata
        assert meta.row_group(0).column(0).has_column_index and meta.row_group(0).column(0).has_offset_index
        assert any("DELTA" in e for e in meta.row_group(0).column(0).encodings)
        keys = [k for k in pq.read_table(p, columns=["doc_id"])["doc_id"].to_pylist() if k is not None]
        assert keys == sorted(keys) and (last is None or not keys or keys[0] >= last)
        last = keys[-1] if keys else last
    one = token_files.read_token_files(spark, str(tmp_path / "t")).select("doc_id", "n_tokens")
    assert "ids" not in one._jdf.queryExecution().executedPlan().toString().split("ReadSchema")[1][:200]


@pytest.mark.parametrize("make", [edge.table, edge.with_repeats, edge.empty])
@pytest.mark.parametrize("capacity", [2048, 64])
def test_packing(spark, make, capacity):
    docs = make(spark)
    texts = [r.text for r in docs.collect()]
    got = packing.pack(docs, WORDS, capacity, least=capacity // 32).collect()
    ids = [x + [1] for x in library(WORDS, texts)] if texts else []
    assert sum(r.length for r in got) == sum(map(len, ids))
    bins: dict = {}
    for r in got:
        assert 0 < r.length <= capacity
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for pieces in bins.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= capacity
    used = [sum(x for _, x in p) for p in bins.values()]
    pad = sum(capacity - u for u in used if u & (u - 1))
    assert pad <= 0.05 * sum(used) + 3 * 2 * capacity


def test_packing_covers_each_document(spark):
    docs = edge.table(spark)
    rows = docs.collect()
    ids = {r.doc_id: x + [1] for r, x in zip(rows, library(WORDS, [r.text for r in rows]))}
    seen: dict = {}
    for r in packing.pack(docs, WORDS).collect():
        assert r.doc_tokens == len(ids[r.doc_id]) and r.ids_crc32 == crc(ids[r.doc_id][r.start : r.start + r.length])
        seen.setdefault(r.doc_id, []).append((r.start, r.length))
    for doc, pieces in seen.items():
        at = 0
        for start, length in sorted(pieces):
            assert start == at
            at += length
        assert at == len(ids[doc])
    assert seen.keys() == ids.keys()


def test_harmonic_classes():
    assert packing.piece_lengths(2048 * 2 + 1024 + 64 + 7) == [2048, 2048, 1024, 64, 7]
    p = packing.HarmonicPacker(100)
    out = [r for i in range(6) for r in p.add(i, 0, 33, np.zeros(33, np.uint32), 33)]
    assert [r[5] for r in out] == [0, 0, 0, 1, 1, 1] and [r[6] for r in out[:3]] == [0, 33, 66]
    for i in range(3):
        p.add(i, 0, 40, np.zeros(40, np.uint32), 40)
    rest = p.finish()
    assert sum(r[2] for r in rest) == 40 and not p.open


def test_edits_follow_recounts():
    model, t = bpe.NumpyBPE(BYTES), Tokenizer.from_str(BYTES)
    rng = random.Random(5)
    for x in [y or "" for y in edge.texts()][:30] + noise(150, 6):
        x = x[:2000]
        w = model.split(x)
        now = edit_counts.EditedText(model, x, *edit_counts.leaves_of(w, model.count_words(w)))
        for _ in range(5):
            n = len(now.text)
            s = rng.randrange(n + 1)
            now.edit(s, s + rng.randrange(40), rng.choice(["", "<|endoftext|>", "new words here", "'s", "\n", " "]))
            assert now.tree.total == len(t.encode(now.text, add_special_tokens=False).ids)
            assert now.tree.length == len(now.text)


@pytest.mark.parametrize("make", [edge.table, edge.with_repeats, edge.empty])
def test_edit_query(spark, make):
    docs = make(spark)
    trees = three_edits(edit_counts.build(docs, BYTES))
    rows = edit_counts.apply_edits(trees, BYTES, texts_out=True).collect()
    assert len(rows) == docs.count()
    if rows:
        assert [r.n_tokens_edited for r in rows] == [len(x) for x in library(BYTES, [r.text for r in rows])]
        assert all(sum(r.seg_chars) == len(r.text) and sum(r.seg_tokens) == r.n_tokens_edited for r in rows)
        long = [r for r in rows if r.n_chars_edited > 20_000]
        assert all(r.chars_encoded < r.n_chars_edited / 5 for r in long)
