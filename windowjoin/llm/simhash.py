"""SimHash near-duplicates: positional-byte index, count filter, verification, components.

``fingerprints`` hashes every word shingle of a whole text (XXH64, seed 42) and sets the
bits that over half of the hashes have. Fingerprints at ``most`` differing bits or fewer
are linked. Of the eight bytes of two linked fingerprints at most ``most`` differ, so at
least 8-most positional bytes are shared: that is the guaranteed minimum ``least``. The
index lists, for every choice of ``least`` positions, the distinct fingerprints by the
bytes there - the intersections of so many lists of single positional bytes, which alone
would hold 1/256 of everything each. In a list the shared positional bytes of a pair are
tallied, pairs that reach the minimum are verified bit by bit.

Nothing emits all pairs of a list: a list is searched breadth first, each fingerprint
taken off compares with those not reached yet, and a fingerprint reached gives one edge to
the root of its search; so a list of g fingerprints gives g-1 edges at most, connected
as its pairs are. A list longer than ``BLOCK`` is searched block by block, and its blocks
then meet two by two in tasks of their own. Components come from contracting each node
into its least neighbour until no edge is left.

Defined cases: a null or empty text, or one of white space only, has fingerprint zero
and is linked like any other; fewer words than a shingle make one shingle of all words;
equal texts share a fingerprint, hence a component; a component's id is its least
doc_id, null ids left aside; an empty table gives an empty table; extra columns are
not read. ``keep_one`` keeps one of the rows with one id and one text, and of rows with one
id and different texts those that are the least of their component.
"""

from __future__ import annotations

from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from windowjoin.llm import common

BLOCK = 4096


def shingle_hashes(text: bytes, width: int) -> list[int]:
    """XXH64 (seed 42) of each run of ``width`` lower-cased words, joined by spaces."""
    import xxhash

    words = text.lower().split()  # of bytes: A-Z only; space and 9 to 13 only
    if not words:
        return []
    line = b" ".join(words)
    if len(words) <= width:
        return [xxhash.xxh64_intdigest(line, 42)]
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = [0, *(ends[: len(words) - width] + 1).tolist()]
    pieces = [line[a:b] for a, b in zip(starts, ends[width - 1 :].tolist(), strict=True)]
    return list(map(xxhash.xxh64_intdigest, pieces, repeat(42)))


def majority(hashes: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Fingerprints of consecutive groups of hashes; an empty group has zero."""
    out = np.zeros(len(counts), np.uint64)
    some = np.flatnonzero(counts)
    if not len(some):
        return out
    ends = np.cumsum(counts)
    at = 0
    while at < len(some):  # a bounded number of bit rows at once; a longer text alone
        base = ends[some[at]] - counts[some[at]]
        to = max(at + 1, int(np.searchsorted(ends[some], base + 200_000, side="right")))
        group = some[at:to]
        if to == at + 1:
            set_bits = np.zeros((1, 64), np.int64)
            for k in range(int(base), int(ends[group[0]]), 200_000):
                piece = hashes[k : min(k + 200_000, int(ends[group[0]]))]
                set_bits += np.unpackbits(piece.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        else:
            piece = hashes[base : ends[group[-1]]]
            bits = np.unpackbits(piece.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
            set_bits = np.add.reduceat(bits, ends[group] - counts[group] - base, axis=0, dtype=np.int32)
        over = (2 * set_bits > counts[group][:, None]).astype(np.uint8)
        out[group] = np.packbits(over, axis=1, bitorder="little").view(np.uint64).ravel()
        at = to
    return out


def fingerprints(docs: DataFrame, width: int = 4, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The columns ``keep``, which are longs, and fp: the 64-bit fingerprint as a signed long."""
    common.ship(docs.sparkSession)

    def rows(batches):
        for batch in batches:
            for part in common.cut(batch, most=4 << 20):
                data, ends = common.utf8(part.column("text"))
                raw, at = data.tobytes(), ends.tolist()
                lists = [shingle_hashes(raw[a:b], width) for a, b in zip(at[:-1], at[1:], strict=True)]
                counts = np.fromiter(map(len, lists), np.int64, len(lists))
                flat = np.fromiter((h for x in lists for h in x), np.uint64, int(counts.sum()))
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), pa.array(majority(flat, counts).view(np.int64))], names=[*keep, "fp"])

    return common.texts(docs, *keep).mapInArrow(rows, ", ".join(f"{c} long" for c in (*keep, "fp")))


# -- the index ---------------------------------------------------------------------------


def position_keys(fp: np.ndarray, least: int) -> np.ndarray:
    """Keys of every choice of ``least`` byte positions, one column each, as signed longs.

    Up to four bytes and the number of the choice fit a long; longer choices are mixed,
    which can only put more fingerprints into one list.
    """
    octets = fp.view(np.uint8).reshape(-1, 8).astype(np.uint64)
    out = []
    for number, positions in enumerate(combinations(range(8), least)):
        key = np.full(len(fp), number, np.uint64)
        for p in positions:
            key = key << np.uint64(8) | octets[:, p] if least <= 4 else (key ^ octets[:, p]) * np.uint64(0x100000001B3)
        out.append(key)
    return np.stack(out, axis=1).view(np.int64)


def shared_bytes(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Number of equal positional bytes."""
    return (np.bitwise_xor(a, b).reshape(-1, 1).view(np.uint8) == 0).sum(axis=1)


def search(fp: np.ndarray, most: int, least: int) -> tuple[np.ndarray, np.ndarray]:
    """Edges (member, root) of a forest with the components of the list's links."""
    left = fp
    members, roots = [], []
    while len(left) > 1:
        root, left = left[0], left[1:]
        frontier = [root]
        while frontier and len(left):
            now = frontier.pop()
            near = shared_bytes(left, now) >= least
            near[near] = np.bitwise_count(left[near] ^ now) <= most
            if near.any():
                found = left[near]
                members.append(found)
                roots.append(np.full(len(found), root))
                frontier.extend(found)
                left = left[~near]
    none = np.zeros(0, np.uint64)
    return (np.concatenate(members), np.concatenate(roots)) if members else (none, none)


def runs(batches, *names: str):
    """Rows of consecutive equal first columns as arrays, a run in pieces of BLOCK at most.

    Yields (column arrays, is this the run's first piece, its last).
    """
    held = [np.zeros(0, np.int64) for _ in names]
    begun = False
    for batch in batches:
        cols = [np.concatenate((h, batch.column(n).to_numpy())) for h, n in zip(held, names, strict=True)]
        key = cols[0]
        edge = np.concatenate(([0], np.flatnonzero(key[1:] != key[:-1]) + 1, [len(key)])) if len(key) else np.zeros(1, np.int64)
        last = edge[-2] if len(edge) > 1 else 0
        size = np.diff(edge)[:-1]
        want = size > 1  # and the piece that ends a run begun before
        if begun and len(want):
            want[0] = True
        for a, n in zip(edge[:-2][want].tolist(), size[want].tolist(), strict=True):
            yield from _pieces([c[a : a + n] for c in cols], begun and a == 0, True)
        if last > 0:
            begun = False
        held = [c[last:] for c in cols]
        while len(held[0]) > 2 * BLOCK:
            yield [c[:BLOCK] for c in held], not begun, False
            begun, held = True, [c[BLOCK:] for c in held]
    if len(held[0]):
        yield from _pieces(held, begun, True)


def _pieces(cols: list[np.ndarray], begun: bool, ends: bool):
    n = len(cols[0])
    for k in range(0, n, BLOCK):
        yield [c[k : k + BLOCK] for c in cols], not begun and k == 0, ends and k + BLOCK >= n


EDGE_SCHEMA = "a long, b long, kind int"


def _edge_batch(a: list[np.ndarray], b: list[np.ndarray], kind: list[np.ndarray]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.concatenate(a)), pa.array(np.concatenate(b)), pa.array(np.concatenate(kind))], names=["a", "b", "kind"])


def links(distinct: DataFrame, most: int = 4) -> DataFrame:
    """Edges (a, b) between distinct fingerprints ``fp`` that connect what linked pairs connect."""
    spark = distinct.sparkSession
    common.ship(spark)
    least = max(0, 8 - most)
    if least == 0:
        raise ValueError("more than 7 differing bits leave no shared byte to look for")

    def keys(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 20_000):
                fp = batch.column("fp").slice(at, 20_000).to_numpy().view(np.uint64)
                k = position_keys(fp, least)
                yield pa.RecordBatch.from_arrays([pa.array(k.ravel()), pa.array(np.repeat(fp.view(np.int64), k.shape[1]))], names=["key", "fp"])

    def forest(fp: np.ndarray, out: list[list]) -> None:
        member, root = search(np.unique(fp).view(np.uint64), most, least)
        if len(member):
            out[0].append(member.view(np.int64))
            out[1].append(root.view(np.int64))
            out[2].append(np.zeros(len(member), np.int32))

    def lists(batches):
        out: list[list] = [[], [], []]
        for (key, fp), first, last in runs(batches, "key", "fp"):
            forest(fp, out)
            if not (first and last):  # a piece of a long list meets the others later
                out[0].append(key)
                out[1].append(fp)
                out[2].append(np.ones(len(key), np.int32))
            if sum(map(len, out[0])) > 50_000:
                yield _edge_batch(*out)
                out = [[], [], []]
        if out[0]:
            yield _edge_batch(*out)

    found = common.written(distinct.select("fp").mapInArrow(keys, "key long, fp long").repartition("key").sortWithinPartitions("key").mapInArrow(lists, EDGE_SCHEMA), "links")
    edges = found.filter("kind = 0").select("a", "b")
    long_lists = found.filter("kind = 1").select(F.col("a").alias("key"), F.col("b").alias("fp"))
    if long_lists.isEmpty():
        return edges.distinct()

    def cells(batches):
        out: list[list] = [[], [], []]
        for (_, fp), _first, _last in cell_runs(batches):
            forest(fp, out)
            if sum(map(len, out[0])) > 50_000:
                yield _edge_batch(*out)
                out = [[], [], []]
        if out[0]:
            yield _edge_batch(*out)

    sizes = long_lists.groupBy("key").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"))
    block = F.pmod(F.xxhash64("fp"), F.col("blocks")).cast("int")
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    spread = long_lists.join(sizes, "key").withColumn("own", block).withColumn("other", other)
    spread = spread.select(F.xxhash64("key", F.least("own", "other"), F.greatest("own", "other")).alias("cell"), "fp")
    across = spread.repartition("cell").sortWithinPartitions("cell").mapInArrow(cells, EDGE_SCHEMA)
    return edges.unionByName(across.select("a", "b")).distinct()


def cell_runs(batches):
    """Whole cells: two blocks hold about 2 * BLOCK fingerprints, which is the bound here."""
    parts: list[list[np.ndarray]] = [[], []]
    for (cell, fp), _first, last in runs(batches, "cell", "fp"):
        parts[0].append(cell)
        parts[1].append(fp)
        if last:
            yield [np.concatenate(p) for p in parts], True, True
            parts = [[], []]


# -- components --------------------------------------------------------------------------


def components(edges: DataFrame) -> DataFrame:
    """(node, root): the root is the same for all nodes of a component, edges being (a, b).

    Each round every node goes into its least neighbour, itself included, and edges are
    drawn again between the nodes they went into; at least half of the nodes that still
    have edges go, so rounds grow with the logarithm. The maps of the rounds are then
    applied one after the other.
    """
    both = lambda e: e.filter("a <> b").select("a", "b").unionByName(e.filter("a <> b").select(F.col("b").alias("a"), F.col("a").alias("b")))
    now = common.written(edges.select("a", "b"), "edges")
    maps: list[DataFrame] = []
    while not now.filter("a <> b").isEmpty():
        into = common.written(both(now).groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("into")).withColumnRenamed("a", "node"), "into")
        maps.append(into)
        ends = now.filter("a <> b")
        for side in ("a", "b"):
            ends = ends.join(into.select(F.col("node").alias(side), F.col("into").alias(f"{side}_into")), side)
        now = common.written(ends.select(F.col("a_into").alias("a"), F.col("b_into").alias("b")).filter("a <> b").distinct(), "edges")
    if not maps:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("root")).filter("false")
    # every map's trees have depth of their own: follow within a map until it is flat
    flat = [_flatten(m) for m in maps]
    out = flat[0]
    for step in flat[1:]:
        out = common.written(out.join(step.select(F.col("node").alias("root"), F.col("root").alias("next")), "root", "left").select("node", F.coalesce("next", "root").alias("root")), "roots")
    return out


def _flatten(into: DataFrame) -> DataFrame:
    """(node, root) of a map whose chains go down to a node that maps to itself."""
    out = into.select("node", F.col("into").alias("root"))
    while True:
        further = common.written(out.join(out.select(F.col("node").alias("root"), F.col("root").alias("next")), "root", "left").select("node", "root", F.coalesce("next", "root").alias("next")), "roots")
        done = further.filter("next <> root").isEmpty()
        out = further.select("node", F.col("next").alias("root"))
        if done:
            return out


def grouped(docs: DataFrame, width: int, most: int, keep: tuple[str, ...]) -> DataFrame:
    """``keep``, fp, root (a fingerprint of the component) and component_id of every row."""
    table = common.written(fingerprints(docs, width, keep), "fingerprints")
    distinct = common.written(table.groupBy("fp").agg(F.min("doc_id").alias("first")), "distinct")
    roots = components(links(distinct, most))
    joined = distinct.join(roots.select(F.col("node").alias("fp"), "root"), "fp", "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    rooted = common.written(joined, "rooted")
    least = common.written(rooted.groupBy("root").agg(F.min("first").alias("component_id")), "least")
    labels = common.written(rooted.join(least, "root").select("fp", "root", "component_id"), "labels")
    return table.join(labels, "fp").select(*keep, "fp", "root", "component_id")


def near_duplicates(docs: DataFrame, width: int = 4, most: int = 4) -> DataFrame:
    """doc_id, fp and component_id, the least doc_id that is reachable over links."""
    return grouped(docs, width, most, ("doc_id",)).select("doc_id", "fp", "component_id")


def digest(found: DataFrame) -> DataFrame:
    """The fingerprint as 16 lower-case hexadecimal digits."""
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, width: int = 4, most: int = 4) -> DataFrame:
    """One row of ``docs``, that of the least doc_id, of each component; null ids stay."""
    found = common.written(grouped(docs.withColumn("text_id", common.text_id()), width, most, ("doc_id", "text_id")), "grouped")
    kept = found.filter("doc_id = component_id").groupBy("root").agg(F.first("doc_id").alias("kept__id"), F.min("text_id").alias("kept__text"))
    return common.keep_rows(docs, kept, found.select("doc_id", "text_id"))
