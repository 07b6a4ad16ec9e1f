import random

import corpus_pipeline
import numpy as np
import pytest

from tests.llm import edge
from windowjoin.llm import near_copies, simhash

SF = "/root/testdata/sf0.001"


def planted(seed: int = 5) -> list[str]:
    """Texts with copies of which a few single words differ, and texts of their own."""
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(6))
    out = []
    for k in range(60):
        base = [word() for _ in range(rng.randrange(60, 400))]
        out.append(" ".join(base))
        for edits in range(1, 1 + len(base) // 60):
            copy = list(base)
            for at in rng.sample(range(len(copy)), edits * (1 + k % 3)):
                copy[at] = word()
            out.append(" ".join(copy))
    return out


def kept_by_brute_force(texts: list, width: int = 5, at_least: float = 0.8) -> list[int]:
    def shingles(t):
        w = (t or "").encode().lower().split()
        return {tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()

    sets = [shingles(t) for t in texts]
    root = list(range(len(sets)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            if a == b or (a and b and len(a & b) * 10 >= round(at_least * 10) * len(a | b)):
                x, y = sorted((find(i), find(j)))
                root[y] = x
    return sorted({find(i) for i in range(len(sets))})


@pytest.mark.parametrize("rows", [planted(), edge.texts()], ids=["planted", "edge"])
def test_stage_keeps_one_of_all_texts_at_similarity_of_four_fifths(spark, rows):
    docs = edge.table(spark, rows)
    kept = corpus_pipeline.stage_near_duplicates(spark, docs, SF)
    assert sorted(r.doc_id for r in kept.select("doc_id").collect()) == kept_by_brute_force(rows)


@pytest.mark.parametrize("keep_one", [near_copies.keep_one, simhash.keep_one])
def test_repeated_rows_leave_one(spark, keep_one):
    docs = edge.with_repeats(spark)
    once = sorted(r.doc_id for r in keep_one(edge.table(spark)).collect())
    kept = keep_one(docs)
    assert kept.columns == docs.columns
    assert sorted(r.doc_id for r in kept.collect() if r.doc_id is not None) == once == sorted(set(once))
    assert kept.filter("doc_id is null").count() == 1
    assert keep_one(edge.empty(spark)).count() == 0


@pytest.mark.parametrize("keep_one", [near_copies.keep_one, simhash.keep_one])
def test_one_id_with_different_texts(spark, keep_one):
    """Row 1 is twice with one text and once with another one; the other one has a copy of lesser id."""
    mine, other = (" ".join(f"{w}{k}" for k in range(80)) for w in ("ab", "xyz"))
    rows = [(1, mine), (1, mine), (1, other), (0, other), (2, mine), (3, "something else altogether is here")]
    kept = keep_one(spark.createDataFrame(rows, "doc_id long, text string"))
    assert sorted(map(tuple, kept.collect())) == [(0, other), (1, mine), (3, rows[-1][1])]


def test_large_components_go_by_blocks(spark, monkeypatch):
    rng = random.Random(3)
    base = [f"word{rng.randrange(10**6)}" for _ in range(300)]
    rows = ["wholly different words stand in this text"]
    for k in range(40):
        copy = list(base)
        copy[rng.randrange(300)] = f"other{k}"
        rows.append(" ".join(copy))
    whole = near_copies.keep_one(edge.table(spark, rows)).count()
    monkeypatch.setattr(near_copies, "BLOCK_BYTES", 5000)
    assert whole == near_copies.keep_one(edge.table(spark, rows)).count() == 2


def test_similar_is_exact_at_the_bound():
    assert near_copies.similar(np.arange(5), np.arange(4), 0.8)
    assert not near_copies.similar(np.arange(10), np.arange(7), 0.8)
    assert near_copies.similar(np.arange(0), np.arange(0), 0.8) and not near_copies.similar(np.arange(0), np.arange(3), 0.8)


def test_candidates_come_from_the_simhash_index_too(spark, monkeypatch):
    """With no candidate from the minwise index the SimHash components still find what they link, and only that is kept as copies which is similar."""
    rng = random.Random(11)
    base = [f"w{rng.randrange(10**6)}" for _ in range(4000)]
    near = [*base[:-1], "other"]
    rows = [" ".join(base), " ".join(near), " ".join(f"x{k}" for k in range(300))]
    prints = simhash.fingerprints(edge.table(spark, rows), 5).orderBy("doc_id").collect()
    assert bin((prints[0].fp ^ prints[1].fp) & (2**64 - 1)).count("1") <= near_copies.MOST
    monkeypatch.setattr(near_copies, "candidates", lambda distinct: distinct.selectExpr("node as a", "node as b").filter("false"))
    assert sorted(r.doc_id for r in near_copies.keep_one(edge.table(spark, rows)).collect()) == [0, 2]


def test_a_simhash_link_alone_is_no_copy(spark, monkeypatch):
    monkeypatch.setattr(near_copies, "by_fingerprints", lambda prints: prints.crossJoin(prints.selectExpr("node as b")).selectExpr("node as a", "b"))
    rows = [f"text {k} has words of its own like {k * k} and {k + 7}" for k in range(6)]
    assert near_copies.keep_one(edge.table(spark, rows)).count() == 6
