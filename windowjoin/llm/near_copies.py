"""Near copies by the Jaccard similarity of word shingles: SimHash, minwise positional bytes, then exact sets.

The shingles are those of ``simhash``, and so is the first source of candidates: texts whose
64-bit fingerprints link at ``MOST`` differing bits, found by its index of positional bytes, its
count filter, its verification and its components. Similar texts lie further apart than that
as a rule, so a second index follows. Its fingerprint of a text is one byte at each of
``BANDS * ROWS`` positions, taken from the shingle that is least under the position's own
order; two texts agree at a position with the probability of their similarity. The index
lists the distinct shingle sets by the ``ROWS`` least shingles of each band (64-bit keys).
In a list the shared positional bytes of a pair are counted, and pairs with ``LEAST`` or
more are candidates. At a similarity of 0.8 a pair is in no common list with a probability
of (1 - 0.8**4)**20 = 2.7e-5, and falls at the count with less than 1e-5.

Candidates of both are joined into components, the texts of a component are brought together
once, and only there shingle sets are compared, exactly: no fingerprint ever decides a link.
As in ``simhash`` lists and components are searched breadth first, so that g members give
g-1 edges at most, and long ones block by block in tasks of their own.

Defined cases: texts with equal shingle sets, and all texts without words, are copies; null
ids stay; of rows with one id and one text one stays, and of rows with one id and different
texts those that are the least of their component; fewer words than a shingle make one shingle; extra columns are not read.
"""

from __future__ import annotations

from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from windowjoin.llm import common, simhash
from windowjoin.llm.multiset_hash import mixed
from windowjoin.llm.simhash import BLOCK, EDGE_SCHEMA, _edge_batch, components, majority, runs, shingle_hashes

BANDS, ROWS, LEAST = 20, 4, 46
#: differing bits of linked SimHash fingerprints
MOST = 4
#: an odd factor and an offset for each position
_RANDOM = np.random.default_rng(80)
FACTOR = _RANDOM.integers(1, 2**63, BANDS * ROWS, np.uint64) * np.uint64(2) + np.uint64(1)
OFFSET = _RANDOM.integers(0, 2**64, BANDS * ROWS, np.uint64)
KEYS = [f"k{i}" for i in range(BANDS)]
MARKS = [f"m{i}" for i in range(BANDS * ROWS // 8)]
#: bytes of text in a block of a component
BLOCK_BYTES = 8 << 20


def shingle_set(text: bytes, width: int) -> np.ndarray:
    """The distinct shingle hashes in ascending order."""
    return np.unique(np.array(shingle_hashes(text, width), np.uint64))


def node_of(hashes: np.ndarray) -> int:
    """A name of a shingle set, as a signed long."""
    import xxhash

    return int(np.uint64(xxhash.xxh64_intdigest(hashes.tobytes(), 43)).view(np.int64))


def least_hashes(flat: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The least value at each position of consecutive groups of hashes; an empty group has zeros."""
    out = np.zeros((len(counts), BANDS * ROWS), np.uint64)
    some = np.flatnonzero(counts)
    if len(some):
        starts = (np.cumsum(counts) - counts)[some]
        for j in range(BANDS * ROWS):
            out[some, j] = np.minimum.reduceat((flat ^ OFFSET[j]) * FACTOR[j], starts)
    return out


def band_keys(least: np.ndarray) -> np.ndarray:
    """A signed long for each band."""
    key = np.tile(np.arange(BANDS, dtype=np.uint64), (len(least), 1))
    for r in range(ROWS):
        key = mixed(key + mixed(least[:, r::ROWS]))
    return key.view(np.int64)


def marks_of(least: np.ndarray) -> np.ndarray:
    """The positional bytes, eight to a signed long."""
    return np.ascontiguousarray((least & np.uint64(255)).astype(np.uint8)).view(np.int64)


def forest(n: int, near) -> tuple[np.ndarray, np.ndarray]:
    """Edges (member, root) that connect what ``near(one, others)`` connects."""
    left = np.arange(n)
    members, roots = [left[:0]], [left[:0]]
    while len(left) > 1:
        root, left = left[0], left[1:]
        frontier = [root]
        while frontier and len(left):
            hit = near(frontier.pop(), left)
            if hit.any():
                found = left[hit]
                members.append(found)
                roots.append(np.full(len(found), root))
                frontier.extend(found)
                left = left[~hit]
    return np.concatenate(members), np.concatenate(roots)


def by_marks(nodes: np.ndarray, marks: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Edges between the nodes of a list that share LEAST positional bytes."""
    nodes, index = np.unique(nodes, return_index=True)
    octets = np.stack([m[index] for m in marks], axis=1).view(np.uint8)
    member, root = forest(len(nodes), lambda i, left: (octets[left] == octets[i]).sum(axis=1) >= LEAST)
    return nodes[member], nodes[root]


def similar(one: np.ndarray, other: np.ndarray, at_least: float) -> bool:
    """Is the Jaccard similarity of two ascending sets ``at_least`` so much?"""
    small, large = (one, other) if len(one) <= len(other) else (other, one)
    if len(small) < at_least * len(large) - 1e-9:
        return False
    if not len(small):
        return True
    at = np.minimum(np.searchsorted(large, small), len(large) - 1)
    both = int((large[at] == small).sum())
    return both >= at_least * (len(one) + len(other) - both) - 1e-9


def signatures(docs: DataFrame, width: int) -> DataFrame:
    """(doc_id, text_id, node, SimHash fingerprint, band keys, marks) of every row."""
    common.ship(docs.sparkSession)
    names = ["doc_id", "text_id", "node", "fp", *KEYS, *MARKS]

    def rows(batches):
        for batch in batches:
            for part in common.cut(batch, most=4 << 20):
                data, ends = common.utf8(part.column("text"))
                raw, at = data.tobytes(), ends.tolist()
                lists = [np.array(shingle_hashes(raw[a:b], width), np.uint64) for a, b in zip(at[:-1], at[1:], strict=True)]
                fp = majority(np.concatenate(lists), np.fromiter(map(len, lists), np.int64, len(lists)))
                sets = [np.unique(x) for x in lists]
                counts = np.fromiter(map(len, sets), np.int64, len(sets))
                least = least_hashes(np.concatenate(sets), counts)
                nodes = pa.array([node_of(s) for s in sets], pa.int64())
                cols = [pa.array(np.ascontiguousarray(c)) for m in (band_keys(least), marks_of(least)) for c in m.T]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text_id"), nodes, pa.array(fp.view(np.int64)), *cols], names=names)

    known = common.texts(docs, "doc_id").withColumn("text_id", common.text_id())
    return known.mapInArrow(rows, ", ".join(f"{n} long" for n in names))


def _cells(rows: DataFrame, sizes: DataFrame, group: str, node: str) -> DataFrame:
    """Each row once for every pair of blocks that its block is in; ``sizes`` has (group, blocks)."""
    own = F.pmod(F.xxhash64(node), F.col("blocks")).cast("int")
    spread = rows.join(sizes, group).withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    cell = F.xxhash64(group, F.least("own", "other"), F.greatest("own", "other"))
    return spread.withColumn("cell", cell).drop("own", "other", "blocks", group).repartition("cell").sortWithinPartitions("cell")


def _edges(found):
    """Batches of the edges that are found one list after the other; ``found`` yields (a, b, kind)."""
    out: list[list] = [[], [], []]
    n = 0
    for a, b, kind in found:
        if len(a):
            for held, new in zip(out, (a, b, np.full(len(a), kind, np.int32)), strict=True):
                held.append(new)
            n += len(a)
        if n > 50_000:
            yield _edge_batch(*out)
            out, n = [[], [], []], 0
    if out[0]:
        yield _edge_batch(*out)


def candidates(distinct: DataFrame) -> DataFrame:
    """Edges (a, b) between nodes that share a list and LEAST positional bytes."""
    names = ["key", "node", *MARKS]

    def keys(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 10_000):
                part = batch.slice(at, 10_000)
                key = np.stack([part.column(k).to_numpy() for k in KEYS], axis=1).ravel()
                rest = [pa.array(np.repeat(part.column(c).to_numpy(), BANDS)) for c in ("node", *MARKS)]
                yield pa.RecordBatch.from_arrays([pa.array(key), *rest], names=names)

    def lists(batches):
        def found():
            for (key, node, *marks), first, last in runs(batches, *names):
                yield *by_marks(node, marks), 0
                if not (first and last):  # a piece of a long list meets the others later
                    yield key, node, 1

        return _edges(found())

    def cells(batches):
        def found():
            parts: list[list] = []
            for cols, _, last in runs(batches, "cell", "node", *MARKS):
                parts.append(cols[1:])
                if last:
                    node, *marks = map(np.concatenate, zip(*parts, strict=True))
                    yield *by_marks(node, marks), 0
                    parts = []

        return _edges(found())

    listed = distinct.mapInArrow(keys, ", ".join(f"{n} long" for n in names)).repartition("key").sortWithinPartitions("key")
    out = common.written(listed.mapInArrow(lists, EDGE_SCHEMA), "candidates")
    edges = out.filter("kind = 0").select("a", "b")
    long_lists = out.filter("kind = 1").select(F.col("a").alias("key"), F.col("b").alias("node"))
    if not long_lists.isEmpty():
        sizes = long_lists.groupBy("key").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"))
        spread = _cells(long_lists.join(distinct.select("node", *MARKS), "node"), sizes, "key", "node")
        edges = edges.unionByName(spread.mapInArrow(cells, EDGE_SCHEMA).select("a", "b"))
    return edges.distinct()


def by_fingerprints(prints: DataFrame) -> DataFrame:
    """Edges (a, b) that connect the nodes with one SimHash fingerprint or linked ones; ``prints`` has (node, fp)."""
    prints = common.written(prints.distinct(), "prints")
    roots = components(simhash.links(prints.select("fp").distinct(), MOST)).withColumnRenamed("node", "fp")
    rooted = common.written(prints.join(roots, "fp", "left").select("node", F.coalesce("root", "fp").alias("root")), "rooted")
    least = rooted.groupBy("root").agg(F.min("node").alias("b"))
    return rooted.join(least, "root").filter("node <> b").select(F.col("node").alias("a"), "b")


def links(docs: DataFrame, distinct: DataFrame, prints: DataFrame, width: int, at_least: float) -> DataFrame:
    """Edges (a, b) that connect the nodes whose shingle sets are similar."""
    roots = components(by_fingerprints(prints).unionByName(candidates(distinct)))
    wanted = common.written(distinct.select("node", "text_id").join(roots, "node"), "wanted")
    own = common.texts(docs).withColumn("text_id", common.text_id())
    # one exchange by text_id, at every size: the ids wanted grow with the texts
    texts = common.written(own.join(wanted.hint("merge"), "text_id").dropDuplicates(["text_id"]), "texts")
    sizes = texts.groupBy("root").agg(F.ceil((F.sum(F.octet_length("text")) + 1) / BLOCK_BYTES).cast("int").alias("blocks"))

    def compare(batches):
        def rows():
            for batch in batches:
                yield from zip(*(batch.column(c).to_pylist() for c in ("cell", "node", "text")), strict=True)

        def found():
            for _, group in groupby(rows(), key=lambda r: r[0]):
                nodes, sets = [], []
                for _, node, text in group:
                    nodes.append(node)
                    sets.append(shingle_set(text.encode(), width))
                near = lambda i, left: np.fromiter((similar(sets[i], sets[j], at_least) for j in left), bool, len(left))
                member, root = forest(len(nodes), near)
                names = np.array(nodes, np.int64)
                yield names[member], names[root], 0

        return _edges(found())

    return common.written(_cells(texts.select("root", "node", "text"), sizes, "root", "node").mapInArrow(compare, EDGE_SCHEMA), "links").select("a", "b").distinct()


def keep_one(docs: DataFrame, width: int = 5, at_least: float = 0.8) -> DataFrame:
    """One row, that of the least doc_id, of each component of similar texts; null ids stay."""
    table = common.written(signatures(docs, width), "signatures")
    firsts = [F.first(c).alias(c) for c in ("text_id", *KEYS, *MARKS)]  # of one text or of equal sets
    least = F.min(F.when(F.col("doc_id").isNotNull(), F.struct("doc_id", "text_id"))).alias("first")
    distinct = common.written(table.groupBy("node").agg(least, *firsts), "distinct")
    roots = components(links(docs, distinct, table.select("node", "fp"), width, at_least))
    rooted = distinct.select("node", "first").join(roots, "node", "left").select("first", F.coalesce("root", "node").alias("root"))
    kept = rooted.groupBy("root").agg(F.min("first").alias("first")).filter("first is not null")
    kept = kept.select(F.col("first.doc_id").alias("kept__id"), F.col("first.text_id").alias("kept__text"))
    return common.keep_rows(docs, kept, table.select("doc_id", "text_id"))
