import random

import corpus_pipeline
import numpy as np
import pytest

from tests.llm import edge
from windowjoin.llm import suffix_dedup

SF = "/root/testdata/sf0.001"


def test_passages_of_over_50_words_go_and_shorter_ones_stay(spark):
    rng = random.Random(8)
    made = lambda n, most: " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randrange(1, most))) for _ in range(n))
    rows, goes, stays = [], [], []
    for k in range(60):
        n, most = [(51, 6), (55, 8), (60, 8), (50, 8), (30, 10)][k % 5]
        passage = made(n, most)
        (goes if n > 50 else stays).append(passage)
        rows += [f"{made(80, 9)} before{end} {passage} {end}after {made(40, 9)}" for end in "xy"]
    rows.append(" ".join("a" * 51) + " | " + made(60, 9))
    rows.append(made(60, 9) + " | " + " ".join("a" * 51))
    goes.append(" ".join("a" * 51))
    left = [r.text for r in corpus_pipeline.stage_repeats(spark, edge.table(spark, rows), SF).collect()]
    assert len(left) == len(rows)
    assert not any(p in t for p in goes for t in left)
    assert all(sum(p in t for t in left) == 2 for p in stays)


@pytest.mark.parametrize("start,stop,n", [(0, 11, 3), (1, 11, 2), (0, 10, 2), (3, 8, 1), (2, 9, 1), (4, 7, 1)])
def test_whole_words(start, stop, n):
    assert suffix_dedup.whole_words(b"abc def ghi", start, stop) == n


@pytest.mark.parametrize(("span", "q"), [(101, 7), (400, 13), (60, 5)])
def test_a_group_of_texts_is_read_at_once_and_like_each_alone(span, q):
    """numpy is called once a group; no name, context or start reaches into the text beside it."""
    rng = np.random.default_rng(3)
    texts = [rng.integers(97, 99, n, np.uint8).tobytes() for n in (0, 700, span, span - 1, 0, 0, 1500, 401, 3, span + 1, 0)]
    rows = [(str(i), 1, t) for i, t in enumerate(texts * 300)]
    assert len(list(suffix_dedup._groups(rows))) < 10
    together, alone = suffix_dedup.Sampler(span, q), suffix_dedup.Sampler(span, q)
    together.read(texts)
    p = together.samples()
    start, stop = together.bounds(p)
    assert (p + together.tuple <= stop).all()
    for text, at in zip(texts, together.starts, strict=True):
        alone.read([text])
        mine = p[(start == at) & (stop == at + len(text))]
        assert np.array_equal(mine - at, alone.samples())
        for method in ("names", "keys", "contexts"):
            assert np.array_equal(getattr(together, method)(mine), getattr(alone, method)(mine - at))
        few = alone.samples()[::5]
        want = {s for x in few for s in range(x - alone.v + 1, x + 1) if 0 <= s <= len(text) - span}
        assert set(suffix_dedup._starts_near(together, few + at) - at) == want


@pytest.mark.parametrize("n", [0, 1, 50, 5000])
def test_names_are_looked_up_and_made_distinct(n):
    """the lookup agrees with a set, whatever the values' upper bits; parts are in order of names."""
    rng = np.random.default_rng(n)
    names = np.concatenate((rng.integers(0, 2**64, n, np.uint64), rng.integers(0, 40, n, np.uint64), np.full(min(n, 2), 2**64 - 1, np.uint64)))
    distinct, again = suffix_dedup._distinct(names)
    want, count = np.unique(names, return_counts=True)
    assert np.array_equal(distinct, want) and np.array_equal(again, count > 1)
    known, asked = distinct[::2], np.concatenate((names, rng.integers(0, 2**64, 100, np.uint64)))
    hit, at = suffix_dedup.Lookup(known).find(asked)
    assert np.array_equal(hit, np.flatnonzero(np.isin(asked, known))) and np.array_equal(known[at], asked[hit])
    part = suffix_dedup._part(distinct, 51)
    assert (np.diff(part) >= 0).all() and (not n or (part[0] >= 0 and part[-1] < 51))
    rows = suffix_dedup._blocks(part, 3, 1, distinct, again)
    assert b"".join(r[3][: len(r[3]) // 9 * 8] for r in rows) == distinct.tobytes()
