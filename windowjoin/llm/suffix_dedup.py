"""Repeated substrings by difference-cover suffix sampling, over texts of any number.

A byte goes if a string of ``span`` bytes that covers it also starts anywhere else.
Two suffixes can be compared through a sampled pair behind them: with a difference cover
D of period v, for any two starts i and j some k < v has both (i+k) mod v and (j+k) mod v
in D. The classic algorithm takes v = 3 and triples; here v comes from a Singer
difference set (v = q*q+q+1 with q+1 residues, 183 with 14 for q = 13), so that one in
13 suffixes is sampled. As only equality over ``span`` bytes is asked for, the order of
suffixes is kept as names (hashes) of tuples:

1. Sampled tuples. The sampled suffixes' tuples of span-v+1 bytes are named; names that
   occur once in all texts are settled (their suffixes have no partner) and go.
2. Recursion. The others' names are refined by what stands before and behind them, up to
   v-1 bytes on either side: equal refined names settle whole runs of starts at once.
3. Remaining suffixes. For starts i = p-k, the suffixes that share a sampled name are put
   in order of (k bytes before, span-tuple-k bytes behind) and adjacent ones compared,
   for each k < v; equal neighbours are repeats.

Equal texts are one text with a count, so copies cost nothing. Texts are dealt into
buckets by digest; between the steps only names and contexts that occur in the bucket
once move, in packed blocks, and the answers go back to the buckets. A name that is in
very many buckets is not gathered: its starts are settled by names of whole spans
(``hot_buckets``), of which each bucket sends one copy.

Defined cases: a null or empty text, and any text shorter than the span, loses nothing;
equal texts of a span and more lose everything; matches inside one text count, also
overlapping ones; an empty table gives an empty table; extra columns pass through
``remove_repeats`` and are not read elsewhere.
"""

from __future__ import annotations

import hashlib
from itertools import chain, groupby, product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from windowjoin.llm import common
from windowjoin.llm.multiset_hash import mixed

BASE = np.uint64(0x9E3779B97F4A7C15)
BACK = np.uint64(pow(int(BASE), -1, 1 << 64))
BYTE_VALUE = np.random.default_rng(77).integers(1, 2**63, 256, np.uint64) * np.uint64(2) + np.uint64(1)
NAMES, CONTEXTS, SPANS, TEXT = 1, 2, 3, 9
#: names that a task holds before it sends them; a value sent twice counts as two occurrences, which it is
AT_ONCE = 4_000_000


def difference_cover(q: int) -> tuple[int, np.ndarray]:
    """Period and residues of the Singer difference set of a prime q.

    Exponents at which the powers of a primitive element of GF(q**3) lie in a plane.
    """
    v = q * q + q + 1
    for a, b, c in product(range(q), range(q), range(1, q)):
        at, residues = (0, 0, 1), []
        for i in range(q**3 - 1):
            if i < v and at[0] == 0:
                residues.append(i)
            x2, x1, x0 = at
            at = ((x1 + a * x2) % q, (x0 + b * x2) % q, c * x2 % q)
            if at == (0, 0, 1):
                break
        if i == q**3 - 2 and len(residues) == q + 1:
            return v, np.array(residues)
    raise ValueError("q must be prime")


class Sampler:
    """Names of substrings of a group of texts that lie one behind the other; places are those in the group."""

    def __init__(self, span: int, q: int):
        self.span, (self.v, self.residues) = span, difference_cover(q)
        self.tuple = span - self.v + 1
        self.side = self.v - 1
        if self.tuple < 16:
            raise ValueError("the span must be longer than the period")
        self.up = self.down = np.ones(1, np.uint64)

    def _powers(self, n: int) -> None:
        if n >= len(self.up):
            size = max(n + 1, 2 * len(self.up), 1 << 17)
            one = np.ones(1, np.uint64)
            self.up = np.concatenate((one, np.multiply.accumulate(np.full(size, BASE))))
            self.down = np.concatenate((one, np.multiply.accumulate(np.full(size, BACK))))

    def read(self, texts: list[bytes]) -> None:
        size = np.array([len(t) for t in texts], np.int64)
        self.stops = np.cumsum(size)
        self.starts = self.stops - size
        self.n = int(size.sum())
        self._powers(self.n)
        self.data = np.frombuffer(b"".join(texts), np.uint8)
        self.sums = np.zeros(self.n + 1, np.uint64)
        np.cumsum(BYTE_VALUE[self.data] * self.up[: self.n], out=self.sums[1:])

    def bounds(self, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where the texts of the places begin and end."""
        text = np.searchsorted(self.stops, p, side="right")
        return self.starts[text], self.stops[text]

    def name(self, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
        return mixed((self.sums[stop] - self.sums[start]) * self.down[start] + np.uint64(1) * (stop - start).astype(np.uint64))

    def samples(self) -> np.ndarray:
        long = self.stops - self.starts >= self.span
        starts, stops = self.starts[long], self.stops[long]
        periods = -(-(stops - starts) // self.v)
        at = np.repeat(starts, periods) + self.v * common.ranges(np.zeros(len(periods), np.int64), periods)
        p = (at[:, None] + self.residues).ravel()
        return p[p + self.tuple <= np.repeat(stops, periods * len(self.residues))]

    def names(self, p: np.ndarray) -> np.ndarray:
        return self.name(p, p + self.tuple)

    def sides(self, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """How many context bytes there are before the tuple and behind it."""
        start, stop = self.bounds(p)
        return np.minimum(p - start, self.side), np.minimum(stop - p - self.tuple, self.side)

    def keys(self, p: np.ndarray) -> np.ndarray:
        """Refined names: tuple with contexts and the contexts' lengths."""
        before, behind = self.sides(p)
        return mixed(self.name(p - before, p + self.tuple + behind) ^ (before * 1024 + behind).astype(np.uint64))

    def contexts(self, p: np.ndarray) -> np.ndarray:
        """The side bytes before each tuple and behind it, zeros beyond the text."""
        if not len(p):
            return np.zeros((0, 2 * self.side), np.uint8)
        none = np.zeros(self.side, np.uint8)
        around = np.lib.stride_tricks.sliding_window_view(np.concatenate((none, self.data, none)), 2 * self.side + self.tuple)
        out = np.empty((len(p), 2 * self.side), np.uint8)
        out[:, : self.side], out[:, self.side :] = around[p, : self.side], around[p, self.side + self.tuple :]
        before, behind = self.sides(p)
        edge = np.flatnonzero((before < self.side) | (behind < self.side))
        far = np.arange(self.side)
        inside = np.concatenate((far[::-1] < before[edge, None], far < behind[edge, None]), axis=1)
        out[edge] *= inside
        return out


def neighbours(names: np.ndarray, contexts: np.ndarray, before: np.ndarray, behind: np.ndarray) -> np.ndarray:
    """For each row and each k: does another row of the same name agree on k bytes before
    the tuple and on the rest of the span behind it? (rows are distinct)"""
    m, side = len(names), contexts.shape[1] // 2
    out = np.zeros((m, side + 1), bool)
    powers = np.concatenate((np.ones(1, np.uint64), np.multiply.accumulate(np.full(side, BASE))))
    left, right = np.zeros(m, np.uint64), np.zeros(m, np.uint64)
    for t in range(side):
        right += BYTE_VALUE[contexts[:, side + t]] * powers[t]
    for k in range(side + 1):
        rows = np.flatnonzero((before >= k) & (behind >= side - k))
        if len(rows) > 1:
            key = mixed(names[rows] + mixed(left[rows]) * BASE + mixed(right[rows] ^ np.uint64(k)))
            order = np.argsort(key)
            equal = key[order][1:] == key[order][:-1]
            hit = np.zeros(len(rows), bool)
            hit[order[1:][equal]] = True
            hit[order[:-1][equal]] = True
            out[rows[hit], k] = True
        if k < side:
            left += BYTE_VALUE[contexts[:, side - 1 - k]] * powers[k]
            right -= BYTE_VALUE[contexts[:, 2 * side - 1 - k]] * powers[side - 1 - k]
    return out


# -- blocks that move ------------------------------------------------------------------------

BLOCK_SCHEMA = "part int, bucket int, kind int, data binary"
ROW_SCHEMA = "bucket int, kind int, digest string, copies long, text string, data binary"


def _blocks(part: np.ndarray, bucket: int, kind: int, *cols: np.ndarray) -> list[tuple]:
    """One packed block of the columns for each part; rows that are in order of parts stay where they are."""
    if (part[1:] < part[:-1]).any():
        order = np.argsort(part, kind="stable")
        part, cols = part[order], [c[order] for c in cols]
    cuts = np.flatnonzero(np.concatenate(([True], part[1:] != part[:-1], [True]))).tolist() if len(part) else []
    return [(int(part[i]), bucket, kind, b"".join(c[i:j].tobytes() for c in cols)) for i, j in zip(cuts[:-1], cuts[1:], strict=True)]


def _part(names: np.ndarray, parts: int) -> np.ndarray:
    """The part of a name, by its upper bits: names in order are in order of parts."""
    return ((names >> np.uint64(32)) * np.uint64(parts) >> np.uint64(32)).astype(np.int64)


def _block_batch(rows: list[tuple]) -> pa.RecordBatch:
    part, bucket, kind, data = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array(bucket, pa.int32()), pa.array(kind, pa.int32()), pa.array(data, pa.binary())], names=["part", "bucket", "kind", "data"])


def _unpack(data: bytes, *kinds: tuple) -> list[np.ndarray]:
    """Columns of a packed block; a kind is (dtype, items in a row)."""
    n = len(data) // sum(np.dtype(d).itemsize * w for d, w in kinds)
    out, at = [], 0
    for d, w in kinds:
        out.append(np.frombuffer(data, d, n * w, at).reshape((n, w) if w > 1 else n))
        at += n * w * np.dtype(d).itemsize
    return out


def _unique(values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct values, an index of each, and whether it occurs again."""
    distinct, index, n = np.unique(values, return_index=True, return_counts=True)
    return distinct, index, n > 1


def _distinct(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values in order and whether each occurs again, without the places that ``_unique`` sorts along."""
    values = np.sort(values)
    new = np.concatenate((np.ones(min(1, len(values)), bool), values[1:] != values[:-1]))
    first = np.flatnonzero(new)
    return values[first], np.diff(np.append(first, len(values))) > 1


class Lookup:
    """Places of values in sorted ones; most values are not there, which a table of upper bits tells."""

    def __init__(self, known: np.ndarray):
        bits = min(25, len(known).bit_length() + 3)
        self.known, self.shift = known, np.uint64(64 - bits)
        self.some = np.zeros(1 << bits, bool)
        self.some[known >> self.shift] = True

    def find(self, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Indices of the values that are known, and their places."""
        maybe = np.flatnonzero(self.some[values >> self.shift])
        at = np.searchsorted(self.known, values[maybe])
        hit = np.flatnonzero(self.known[np.minimum(at, len(self.known) - 1)] == values[maybe]) if len(self.known) else maybe[:0]
        return maybe[hit], at[hit]


def _rows(batches, *columns: str):
    for batch in batches:
        yield from zip(*((batch.column(c).cast(pa.binary()) if c == "text" else batch.column(c)).to_pylist() for c in columns), strict=True)


def _groups(texts):
    """The rows (digest, copies, bytes) in lists of a bounded number of bytes, one row at least:
    numpy is called once a group, not once a text, of which most are short."""
    group, size = [], 0
    for row in texts:
        if group and size + len(row[2]) > AT_ONCE // 8:
            yield group
            group, size = [], 0
        group.append(row)
        size += len(row[2])
    if group:
        yield group


def _buckets(batches):
    """(bucket, what the other tasks told it, its texts) of consecutive rows.

    The texts, (digest, copies, bytes) with each digest once, are read on as they are
    asked for; a bucket's texts are never held together.
    """
    for bucket, rows in groupby(_rows(batches, "bucket", "kind", "digest", "copies", "text", "data"), key=lambda r: r[0]):
        told, first = [], None
        for row in rows:
            if row[1] == TEXT:
                first = row
                break
            told.append((row[1], row[5]))
        yield bucket, told, _once(chain([first] if first else [], rows))


def _once(rows):
    for digest, same in groupby(rows, key=lambda r: r[2]):
        first = next(same)
        yield digest, first[3] + sum(r[3] for r in same), first[4]


class Plan:
    """The three steps over one table of texts."""

    def __init__(self, docs: DataFrame, span: int = 400, q: int = 13, hot_buckets: int = 256, part_bytes: int = 128 << 20, words: int = 0, enough: int = 400):
        self.docs, self.spark, self.span, self.q, self.hot = docs, docs.sparkSession, span, q, hot_buckets
        self.words, self.enough = words, enough
        common.ship(self.spark)
        self.width = common.shuffle_width(self.spark)
        self.buckets, self.part_bytes = self.width, part_bytes
        total = common.texts(docs).agg(F.sum(F.octet_length("text"))).first()[0] or 0
        self.name_parts = self._parts(9 * (q + 1) / (q * q + q + 1) * total)

    def _parts(self, size: float) -> int:
        """Enough parts that one has ``part_bytes`` at most; a task takes them one after the other."""
        return int(self.width * max(1, -(-size // (self.width * self.part_bytes))))

    def rows(self) -> DataFrame:
        """Distinct texts of each batch with their number, dealt into buckets."""
        buckets = self.buckets

        def deal(batches):
            for batch in batches:
                for part in common.cut(batch, most=8 << 20):
                    data, ends = common.utf8(part.column("text"))
                    raw, at = data.tobytes(), ends.tolist()
                    digests = [hashlib.md5(raw[a:b]).hexdigest() for a, b in zip(at[:-1], at[1:], strict=True)]
                    first: dict[str, int] = {}
                    count: dict[str, int] = {}
                    for i, d in enumerate(digests):
                        first.setdefault(d, i)
                        count[d] = count.get(d, 0) + 1
                    n = len(first)
                    yield pa.RecordBatch.from_arrays(
                        [
                            pa.array([int(d[:12], 16) % buckets for d in first], pa.int32()),
                            pa.array(np.full(n, TEXT, np.int32)),
                            pa.array(first.keys(), pa.string()),
                            pa.array(count.values(), pa.int64()),
                            part.column("text").take(pa.array(first.values(), pa.int64())),
                            pa.nulls(n, pa.binary()),
                        ],
                        names=["bucket", "kind", "digest", "copies", "text", "data"],
                    )

        return common.texts(self.docs).mapInArrow(deal, ROW_SCHEMA)

    def _in_buckets(self, told: DataFrame | None) -> DataFrame:
        rows = self.rows()
        if told is not None:
            rows = rows.unionByName(told.select("bucket", "kind", F.lit(None).cast("string").alias("digest"), F.lit(0).cast("long").alias("copies"), F.lit(None).cast("string").alias("text"), "data"))
        return rows.repartitionById(self.width, F.pmod("bucket", F.lit(self.width))).sortWithinPartitions("bucket", "kind", "digest")

    def _to_parts(self, blocks: DataFrame) -> DataFrame:
        return blocks.repartitionById(self.width, F.pmod("part", F.lit(self.width))).sortWithinPartitions("part")

    def sampled_names(self) -> DataFrame:
        """Step 1: blocks (bucket, kind, data) with the names that have a partner, and whether they are hot."""
        span, q, parts, hot = self.span, self.q, self.name_parts, self.hot

        def local(batches):
            sampler = Sampler(span, q)

            def block(found):
                names, again = _distinct(np.concatenate(found))
                return _block_batch(_blocks(_part(names, parts), bucket, NAMES, names, again))

            for bucket, _, texts in _buckets(batches):
                found, size = [], 0
                for group in _groups(texts):
                    sampler.read([text for _, _, text in group])
                    found.append(sampler.names(sampler.samples()))
                    size += len(found[-1])
                    if size > AT_ONCE:
                        yield block(found)
                        found, size = [], 0
                if size:
                    yield block(found)

        return common.written(self._to_parts(self._in_buckets(None).mapInArrow(local, BLOCK_SCHEMA)).mapInArrow(lambda b: _partners(b, hot), BLOCK_SCHEMA).drop("part"), "names")

    def refined(self, names: DataFrame) -> DataFrame:
        """Steps 2 and 3: blocks with each refined name's repeated starts, and the repeated spans of hot names."""
        span, q = self.span, self.q
        survivors = names.agg(F.sum(F.octet_length("data"))).first()[0] or 0
        parts = self._parts(survivors / 9 * 400)

        def local(batches):
            sampler = Sampler(span, q)

            def contexts_block(cols):
                own, keys, before, behind, contexts = map(np.concatenate, cols)
                keys, index, again = _unique(keys)
                return _block_batch(_blocks(_part(own[index], parts), bucket, CONTEXTS, own[index], keys, before[index].astype(np.uint16), behind[index].astype(np.uint16), again, contexts[index].astype(np.uint8)))

            def spans_block(spans):
                starts, again = _distinct(np.concatenate(spans))
                return _block_batch(_blocks(_part(starts, parts), bucket, SPANS, starts, again))

            for bucket, told, texts in _buckets(batches):
                known, is_hot = _known(told)
                if not len(known):
                    continue
                places = Lookup(known)
                cols: list[list] = [[] for _ in range(5)]
                spans, n_spans, n_contexts = [], 0, 0
                for group in _groups(texts):
                    sampler.read([text for _, _, text in group])
                    p = sampler.samples()
                    own = sampler.names(p)
                    hit, at = places.find(own)
                    if len(near := _spans_near(sampler, p[hit[is_hot[at]]])):
                        spans.append(near)
                        n_spans += len(near)
                    hit = hit[~is_hot[at]]
                    p, own = p[hit], own[hit]
                    if len(p):
                        n_contexts += len(p)
                        for c, x in zip(cols, (own, sampler.keys(p), *sampler.sides(p), sampler.contexts(p)), strict=True):
                            c.append(x)
                    if n_contexts > AT_ONCE // 40:
                        yield contexts_block(cols)
                        cols, n_contexts = [[] for _ in range(5)], 0
                    if n_spans > AT_ONCE:
                        yield spans_block(spans)
                        spans, n_spans = [], 0
                if n_contexts:
                    yield contexts_block(cols)
                if n_spans:
                    yield spans_block(spans)

        def settle(batches):
            side = difference_cover(q)[0] - 1
            for _, group in groupby(_rows(batches, "part", "bucket", "kind", "data"), key=lambda r: r[0]):
                rows = [r[1:] for r in group]
                if spans := [(b, d) for b, kind, d in rows if kind == SPANS]:
                    yield from _answers(spans, SPANS, 1 << 62)
                if rows := [(b, d) for b, kind, d in rows if kind == CONTEXTS]:
                    yield from _settled(rows, side)

        return common.written(self._to_parts(self._in_buckets(names).mapInArrow(local, BLOCK_SCHEMA)).mapInArrow(settle, BLOCK_SCHEMA).drop("part"), "repeats")

    def spans_removed(self, schema: str, row) -> DataFrame:
        """``row(digest, text bytes, run starts, run stops, length of the longest run of repeated
        bytes, copies)`` of every distinct text."""
        span, q, words, enough = self.span, self.q, self.words, self.enough
        names = self.sampled_names()
        repeats = self.refined(names)

        def local(batches):
            sampler = Sampler(span, q)
            columns = [c.split()[0] for c in schema.split(", ")]
            kinds = [pa.string() if c.endswith("string") else pa.binary() if c.endswith("binary") else pa.int64() for c in schema.split(", ")]
            for _bucket, told, texts in _buckets(batches):
                known, is_hot = _known(told)
                hot_names, hot_spans = known[is_hot], _sorted(told, SPANS)
                keys, masks = _masks(told, sampler.v)
                places = Lookup(keys)
                out, size = [], 0
                for group in _groups(texts):
                    runs = _runs(sampler, group, places, masks, hot_names, hot_spans, words, enough)
                    out += [row(digest, text, *found, copies) for (digest, copies, text), found in zip(group, runs, strict=True)]
                    size += sum(len(text) for _, _, text in group)
                    if size > 4 << 20:
                        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=columns)
                        out, size = [], 0
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=columns)

        told = repeats.unionByName(names)
        out = common.written(self._in_buckets(told).mapInArrow(local, schema), "removed")
        common.forget(names, repeats)
        return out


def _partners(batches, hot: int):
    for _, group in groupby(_rows(batches, "part", "bucket", "data"), key=lambda r: r[0]):
        yield from _answers([r[1:] for r in group], NAMES, hot)


def _answers(rows: list[tuple], kind: int, hot: int):
    """To each bucket: its values that occur elsewhere, or in it again, and which are in ``hot`` buckets or more."""
    cols = [_unpack(d, (np.uint64, 1), (np.bool_, 1)) for _, d in rows]
    values, again = (np.concatenate([c[k] for c in cols]) for k in (0, 1))
    bucket = np.repeat([b for b, _ in rows], [len(c[0]) for c in cols])
    order = np.argsort(values, kind="stable")
    s = values[order]
    first = np.flatnonzero(np.concatenate(([True], s[1:] != s[:-1])))
    n = np.diff(np.append(first, len(s)))
    repeated = (n > 1) | np.logical_or.reduceat(again[order], first)
    keep = np.repeat(repeated, n)
    at, is_hot = order[keep], np.repeat(n >= hot, n)[keep]
    if len(at):
        by = np.argsort(bucket[at], kind="stable")
        at, is_hot = at[by], is_hot[by]
        cuts = np.flatnonzero(np.diff(bucket[at])) + 1
        yield _block_batch([(0, int(bucket[g[0]]), kind, values[g].tobytes() + h.tobytes()) for g, h in zip(np.split(at, cuts), np.split(is_hot, cuts), strict=True)])


def _settled(rows: list[tuple], side: int):
    """To each bucket: refined names with a bit for each k whose start is repeated."""
    cols = [_unpack(d, (np.uint64, 1), (np.uint64, 1), (np.uint16, 1), (np.uint16, 1), (np.bool_, 1), (np.uint8, 2 * side)) for _, d in rows]
    names, keys, before, behind, again, contexts = (np.concatenate([c[k] for c in cols]) for k in range(6))
    bucket = np.repeat([b for b, _ in rows], [len(c[0]) for c in cols])
    distinct, index, place, n = np.unique(keys, return_index=True, return_inverse=True, return_counts=True)
    twice = n > 1
    np.logical_or.at(twice, place, again)
    own = names[index]
    # names with two refined names at least, of which one is not settled yet
    _, group, size = np.unique(own, return_inverse=True, return_counts=True)
    open_ = np.zeros(len(size), bool)
    open_[group[~twice]] = True
    work = np.flatnonzero((size[group] > 1) & open_[group])
    bits = np.zeros((len(distinct), side + 1), bool)
    bits[twice] = True
    work = work[np.argsort(own[work], kind="stable")]
    at = 0
    while at < len(work):  # whole names, a bounded number of rows at once
        to = min(len(work), at + 20_000)
        while to < len(work) and own[work[to]] == own[work[to - 1]]:
            to += 1
        w = work[at:to]
        i = index[w]
        bits[w] |= neighbours(own[w], contexts[i], before[i], behind[i])
        at = to
    some = bits.any(axis=1)
    packed = np.packbits(bits, axis=1)
    rows_out = np.flatnonzero(some[place])
    if len(rows_out):
        rows_out = rows_out[np.argsort(bucket[rows_out], kind="stable")]
        cuts = np.flatnonzero(np.diff(bucket[rows_out])) + 1
        yield _block_batch([(0, int(bucket[g[0]]), CONTEXTS, keys[g].tobytes() + packed[place[g]].tobytes()) for g in np.split(rows_out, cuts)])


def _known(told: list[tuple]) -> tuple[np.ndarray, np.ndarray]:
    """Sorted names of a bucket that have partners, and which of them are hot."""
    cols = [_unpack(d, (np.uint64, 1), (np.bool_, 1)) for kind, d in told if kind == NAMES]
    if not cols:
        return np.zeros(0, np.uint64), np.zeros(0, bool)
    names, hot = (np.concatenate([c[k] for c in cols]) for k in (0, 1))
    order = np.argsort(names)
    return names[order], hot[order]


def _sorted(told: list[tuple], kind: int) -> np.ndarray:
    return np.sort(np.concatenate([np.zeros(0, np.uint64), *(_unpack(d, (np.uint64, 1), (np.bool_, 1))[0] for k, d in told if k == kind)]))


def _masks(told: list[tuple], v: int) -> tuple[np.ndarray, np.ndarray]:
    wide = (v + 7) // 8
    cols = [_unpack(d, (np.uint64, 1), (np.uint8, wide)) for kind, d in told if kind == CONTEXTS]
    if not cols:
        return np.zeros(0, np.uint64), np.zeros((0, wide), np.uint8)
    keys, masks = (np.concatenate([c[k] for c in cols]) for k in (0, 1))
    order = np.argsort(keys)
    return keys[order], masks[order]


def _spans_near(sampler: Sampler, p: np.ndarray) -> np.ndarray:
    """Names of the whole spans whose start is less than a period before a sampled place."""
    return sampler.name(s := _starts_near(sampler, p), s + sampler.span) if len(p) else np.zeros(0, np.uint64)


def _starts_near(sampler: Sampler, p: np.ndarray) -> np.ndarray:
    start, stop = sampler.bounds(p)
    first, last = np.maximum(p - sampler.v + 1, start), np.minimum(p, stop - sampler.span)
    some = first <= last
    turns = np.bincount(first[some], minlength=sampler.n + 1) - np.bincount(last[some] + 1, minlength=sampler.n + 1)
    return np.flatnonzero(np.cumsum(turns))


def _runs(sampler: Sampler, group: list[tuple], keys: Lookup, masks: np.ndarray, hot_names: np.ndarray, hot_spans: np.ndarray, words: int = 0, enough: int = 400) -> list[tuple[np.ndarray, np.ndarray, int]]:
    """For each text of the group its maximal removed runs, with ``words`` only of passages of so many
    words or ``enough`` bytes; and the length of its longest run of repeated bytes, whatever its words."""
    none = np.zeros(0, np.int64)
    out, once = [(none, none, 0)] * len(group), []
    for i, (_, copies, text) in enumerate(group):
        if len(text) < sampler.span:
            continue
        if copies == 1:
            once.append(i)
        elif not words or len(text) >= enough or whole_words(text, 0, len(text)) >= words:
            out[i] = np.array([0]), np.array([len(text)]), len(text)
        else:
            out[i] = none, none, len(text)
    if not once or not (len(masks) or len(hot_spans)):
        return out
    sampler.read([group[i][2] for i in once])
    p = sampler.samples()
    repeated = np.zeros(sampler.n, bool)
    if len(masks):
        hit, at = keys.find(sampler.keys(p))
        whole = (masks[at] == np.packbits(np.ones(sampler.v, bool))).all(axis=1)
        repeated[_starts_near(sampler, p[hit[whole]])] = True
        places, at = p[hit[~whole]], at[~whole]
        start, stop = sampler.bounds(places)
        row, k = np.nonzero(np.unpackbits(masks[at], axis=1, count=sampler.v))
        starts = places[row] - k
        repeated[starts[(starts >= start[row]) & (starts + sampler.span <= stop[row])]] = True
    if len(hot_spans):
        near = _starts_near(sampler, p[np.isin(sampler.names(p), hot_names)])
        repeated[near[np.isin(sampler.name(near, near + sampler.span), hot_spans)]] = True
    starts = np.flatnonzero(repeated)
    cuts = np.searchsorted(starts, np.append(sampler.starts, sampler.n))
    for j in np.flatnonzero(np.diff(cuts)).tolist():
        i = once[j]
        out[i] = _of_starts(starts[cuts[j] : cuts[j + 1]] - sampler.starts[j], group[i][2], sampler.span, words, enough)
    return out


def _of_starts(starts: np.ndarray, text: bytes, span: int, words: int, enough: int) -> tuple[np.ndarray, np.ndarray, int]:
    """The runs of one text, of which these spans are repeated."""
    none = np.zeros(0, np.int64)
    passages = np.split(starts, np.flatnonzero(np.diff(starts) > 1) + 1)  # a repeated passage starts spans without a gap
    longest = max(map(len, passages)) - 1 + span
    if words:
        stay = [p for p in passages if p[-1] + span - p[0] >= enough or whole_words(text, int(p[0]), int(p[-1]) + span) >= words]
        starts = np.concatenate([none, *stay])
        if not len(starts):
            return none, none, longest
    apart = np.flatnonzero(np.diff(starts) > span)
    return starts[np.concatenate(([0], apart + 1))], starts[np.concatenate((apart, [len(starts) - 1]))] + span, longest


def whole_words(text: bytes, start: int, stop: int) -> int:
    """Number of the text's words that lie in the run from end to end."""
    inside = lambda at: 0 < at < len(text) and not text[at - 1 : at].isspace() and not text[at : at + 1].isspace()
    return len(text[start:stop].split()) - inside(start) - inside(stop)


def kept_bytes(text: bytes, starts: np.ndarray, stops: np.ndarray) -> bytes:
    if not len(starts):
        return text
    return b"".join(text[a:b] for a, b in zip([0, *stops.tolist()], [*starts.tolist(), len(text)], strict=True))


def repeat_digests(docs: DataFrame, span: int = 400, **options) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans and the digest of the kept bytes of every document."""

    def row(digest, text, starts, stops, longest, copies):
        return digest, len(text), int((stops - starts).sum()), len(starts), hashlib.sha256(kept_bytes(text, starts, stops)).hexdigest()

    found = Plan(docs, span, **options).spans_removed("digest string, n_bytes long, n_removed long, n_spans long, kept_sha256 string", row)
    return _with_digest(docs, "doc_id").join(found, "digest").drop("digest")


#: the least bytes that 51 words can have, and the cover that fits
PASSAGE_SPAN, PASSAGE_Q, PASSAGE_WORDS = 101, 7, 51


def repeats_and_passages(docs: DataFrame, span: int = 400, words: int = PASSAGE_WORDS, **options) -> DataFrame:
    """The columns of ``repeat_digests`` and ``text``: what is left without repeated passages of
    ``words`` words or more, or ``span`` bytes.

    The passages are looked for first, at the least length that so many words can have. Every
    start of a repeated string of ``span`` bytes lies in a run of repeated starts of the short
    length, so only texts with such a run of ``span`` bytes are looked through again.
    """
    if span < PASSAGE_SPAN:
        raise ValueError(f"a span of {PASSAGE_SPAN} bytes or more")
    options = {"q": 13} | options

    def passages(digest, text, starts, stops, longest, copies):
        left = kept_bytes(text, starts, stops).decode("utf-8", "ignore") if len(starts) else None
        again = text.decode() if longest >= span else None
        return digest, left, again, min(copies, 2)

    def spans(digest, text, starts, stops, longest, copies):
        return digest, int((stops - starts).sum()), len(starts), hashlib.sha256(kept_bytes(text, starts, stops)).hexdigest()

    short = Plan(docs, PASSAGE_SPAN, PASSAGE_Q, words=words, enough=span, hot_buckets=options.get("hot_buckets", 256))
    first = short.spans_removed("digest string, left__text string, again__text string, copies long", passages)
    again = first.filter("again__text is not null").select(F.explode(F.array_repeat("again__text", F.col("copies").cast("int"))).alias("text"))
    second = Plan(again, span, **options).spans_removed("digest string, n_removed long, n_spans long, kept_sha256 string", spans)
    changed = first.filter("left__text is not null").select("digest", "left__text").join(second.filter("n_spans > 0"), "digest", "full")
    body = F.coalesce("text", F.lit(""))
    own = docs.select("doc_id", body.alias("text"), F.md5(body.cast("binary")).alias("digest")).join(changed, "digest", "left")
    nothing = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    return own.select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), nothing("n_removed"), nothing("n_spans"), F.coalesce("kept_sha256", F.sha2(F.col("text").cast("binary"), 256)).alias("kept_sha256"), F.coalesce("left__text", "text").alias("text"))


def _with_digest(docs: DataFrame, *keep: str) -> DataFrame:
    return docs.select(*keep, F.md5(F.coalesce("text", F.lit("")).cast("binary")).alias("digest"))


def remove_repeats(docs: DataFrame, span: int = 400, **options) -> DataFrame:
    """``docs``, all columns, with repeated bytes taken out of ``text`` and ``n_chars`` set anew.

    Where a run begins or ends inside a character, what is left of that character goes.
    A text that loses nothing, a null one included, stays as it is.
    """

    def row(digest, text, starts, stops, longest, copies):
        return digest, len(starts), kept_bytes(text, starts, stops).decode("utf-8", "ignore") if len(starts) else None

    found = Plan(docs, span, **options).spans_removed("digest__own string, spans__own long, kept__own string", row)
    changed = found.filter("spans__own > 0")
    own = F.md5(F.coalesce("text", F.lit("")).cast("binary"))
    joined = docs.join(changed, own == F.col("digest__own"), "left")
    text = F.when(F.col("spans__own") > 0, F.col("kept__own")).otherwise(F.col("text"))
    out = [text.alias(c) if c == "text" else F.when(F.col("spans__own") > 0, F.length("kept__own")).otherwise(F.col(c)).cast(docs.schema[c].dataType).alias(c) if c == "n_chars" else F.col(c) for c in docs.columns]
    return joined.select(*out)
