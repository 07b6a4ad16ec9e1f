"""Worker plan: one exchange brings a subwindow's tuples and its probes to one task.

The manager's commands become blocks: a tuple is an insert for its own subwindow and a probe
for each live subwindow of the other side (those without tuples answer nothing). Blocks are
placed by (side, segment of subwindows, share) and sorted by subwindow, inserts first, so a
task reads them as a stream: it builds one subwindow's structure, answers the probes block
by block and forgets it at the next one. What a task holds is one subwindow (``n_sub`` is
the bound) and a bounded slice of candidates, however many probes come.

Structures: ``sorted`` (answers are ranges of places, counts
never make pairs), ``splitter`` (boundaries inherited from the subwindow before, adjusted
from its counts, least and greatest values), ``wideleaf`` (leaves cut at their middle).
A segment starts ``warm`` subwindows early, on inserts only: adjustment settles within
three rounds, so segments are worked on at the same time and the chain is not one task.

Without a window every probe meets all subwindows before it. There a block of probes goes once
to each span, the subwindows of one worker that have ``SPAN`` tuples together; the task holds
their structures and lets the probes pass by all of them.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType

from windowjoin.config import CountWindow, Layout, TimeWindow
from windowjoin.kernels import structures as st
from windowjoin.operators.advisor import choose_index
from windowjoin.plans import window as win
from windowjoin.predicates import NotEqual, Predicate
from windowjoin.runtime import ship, shuffle_width

WARM, INSERT, PROBE, EXPIRE = -1, 0, 1, 2
#: candidates that a task expands at once
AT_ONCE = 1 << 20
#: without a window: tuples of the subwindows that a task holds together, so that a probe comes to it once
SPAN = 1 << 17
#: a probe block's place there: after all subwindows, by the last one that it meets
AFTER = 1 << 40
#: probes that pass by a span's subwindows at once
PROBES = 1 << 15
ADDRESSES = "array<struct<side:string,segment:bigint,share:bigint,sub_id:bigint,op:int>>"
COUNTS = "probe_side string, probe_key bigint, n bigint"
RANGES = "probe_side string, probe_key bigint, sub_id bigint, band int, id_start bigint, id_end bigint, negated boolean, rank_from bigint, rank_to bigint"
LISTS = "probe_side string, probe_key bigint, keys array<bigint>"
PROFILE = "side string, sub_id bigint, kind string, tuples bigint, probes bigint, whole bigint, touched bigint, copied bigint, late_touched bigint, matches bigint, partitions int, largest bigint, mae double"


def commands(prepared: DataFrame, window: win.Window, layout: Layout, extra: tuple[str, ...] = (), chained: bool = True, expiry: bool = False) -> DataFrame:
    """Insert, probe and warm-up rows: (side, segment, share, sub_id, op, value, key, rank, done, opp[, us, late], extra).

    A column ``asks`` says which tuples probe, if not all do. With ``expiry`` the tuple with which a
    subwindow has left the count window for good also sends that subwindow an expire row.
    """
    rows = win.with_subwindows(prepared, window, layout)
    timed = isinstance(window, TimeWindow)
    if timed:
        rows = rows.withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    first, last = win.live_range(window, layout, "opp", "us")
    segment, share, whole = layout.segment if chained else 1, layout.shares, F.lit(0).cast("bigint")
    long = lambda c: c.cast("bigint")
    address = lambda side, sub, op, seg, sh: F.struct(side.alias("side"), long(seg).alias("segment"), long(sh).alias("share"), long(sub).alias("sub_id"), F.lit(op).alias("op"))
    side, sub = F.col("side"), F.col("sub_id")
    other = F.when(side == "S", "R").otherwise("S")
    in_segment = lambda x: F.floor(x / segment) if segment > 1 else x
    all_shares = F.sequence(whole, F.lit(share - 1).cast("bigint"))
    mine = F.expr(f"pmod(xxhash64(rank div {max(1, layout.n_sub)}), {share})") if share > 1 else whole
    nobody = F.array().cast(ADDRESSES)
    known, asks = F.col("value").isNotNull(), F.col("asks") if "asks" in rows.columns else F.lit(True)
    sent = [
        F.when(known, F.transform(all_shares, lambda k: address(side, sub, INSERT, in_segment(sub), k))).otherwise(nobody),
        F.when(known & asks & (first <= last), F.transform(F.sequence(first, last), lambda x: address(other, x, PROBE, in_segment(x), mine))).otherwise(nobody),
    ]
    if segment > 1:  # the last subwindows of a segment also warm the next one up
        near_end = F.pmod(sub, F.lit(segment)) >= segment - layout.warm
        sent.append(F.when(known & near_end, F.transform(all_shares, lambda k: address(side, sub, WARM, in_segment(sub) + 1, k))).otherwise(nobody))
    if expiry and isinstance(window, CountWindow):
        out = F.col("rank") - window.size
        sent.append(F.when((out > 0) & (out % layout.n_sub == 0), F.array(address(side, F.expr(f"(rank - {window.size}) div {layout.n_sub} - 1"), EXPIRE, F.expr(f"(rank - {window.size}) div {layout.n_sub} - 1"), whole))).otherwise(nobody))
    keep = ["value", "key", "rank", "done", "opp", *(["us"] if timed else []), *(["late"] if "late" in rows.columns else []), *extra]
    return rows.select(F.explode(F.concat(*sent)).alias("to"), *keep).select("to.*", *keep)


def place(sent: DataFrame, layout: Layout) -> DataFrame:
    """The exchange: round robin over ``slots`` workers a side, else over the shuffle's partitions."""
    if not layout.slots:
        width = shuffle_width(sent.sparkSession)
        turn = F.pmod(2 * (F.col("segment") + F.col("share")) + F.when(F.col("side") == "R", 1).otherwise(0), F.lit(width))
        return sent.repartitionById(width, turn.cast("int"))
    turn = F.pmod(F.col("segment") + F.col("share"), F.lit(layout.slots)) + F.when(F.col("side") == "R", layout.slots).otherwise(0)
    return sent.repartitionById(2 * layout.slots, turn.cast("int"))


@dataclass(frozen=True)
class Plan:
    """What a task is told."""

    window: win.Window
    layout: Layout
    choose: Callable[[int], str]
    result: str
    negated: bool
    bands: int
    closed: tuple  # per band: (lo closed if S probes, if R probes, hi closed if S probes, if R probes)
    extra: tuple[str, ...]
    n_bat: int
    chained: bool
    adjust: bool = True
    found: bool = False


def bounded(rows: DataFrame, pred: Predicate, probe_is_s: Column, asks: Column) -> tuple[DataFrame, tuple]:
    """The rows with each band's bounds for probes (null: open), and which ends belong to it."""
    value = F.col("value")
    if isinstance(pred, NotEqual):
        from_s, from_r = [pred.equal_range(value)], [pred.equal_range(value)]
    else:
        from_s, from_r = pred.bounds(value), pred.mirrored().bounds(value)
    cols: dict[str, Column] = {}
    closed = []
    for k, (a, b) in enumerate(zip(from_s, from_r, strict=True)):
        for end in ("lo", "hi"):
            x, y = getattr(a, end), getattr(b, end)
            if x is not None or y is not None:
                nothing = F.lit(None)
                cols[f"{end}{k}"] = F.when(asks, F.when(probe_is_s, nothing if x is None else x).otherwise(nothing if y is None else y))
        closed.append((a.lo_closed, b.lo_closed, a.hi_closed, b.hi_closed))
    return rows.withColumns(cols) if cols else rows, tuple(closed)


PACKED = "side string, op int, first bigint, last bigint, turn bigint, rows binary"


def packed(prepared: DataFrame, pred: Predicate, window: win.Window, layout: Layout, extra: tuple[str, ...], chained: bool) -> tuple[DataFrame, tuple]:
    """The commands with their tuples in blocks: a block of inserts has one subwindow, a block of
    probes those of one side that meet the same subwindows, in value order. What is sent to each of
    a window's subwindows is then a few blocks and not a row for every probe."""
    rows = win.with_subwindows(prepared, window, layout)
    timed = isinstance(window, TimeWindow)
    if timed:
        rows = rows.withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    first, last = win.live_range(window, layout, "opp", "us")
    asks = F.col("asks") if "asks" in rows.columns else F.lit(True)
    rows, closed = bounded(rows, pred, F.col("side") == "S", asks)
    bounds = [c for c in rows.columns if c[:2] in ("lo", "hi") and c[2:].isdigit()]
    keep = ["value", "key", "rank", "done", "opp", *(["us"] if timed else []), *(["late"] if "late" in rows.columns else []), *extra, *bounds]
    # probes of no subwindow have first > last
    sent = rows.filter("value is not null").select("side", "sub_id", F.when(asks, first).otherwise(1).cast("bigint").alias("first__sub"), F.when(asks, last).otherwise(0).cast("bigint").alias("last__sub"), *keep)
    n_sub = layout.n_sub

    def pack(batches):
        for batch in batches:
            if batch.num_rows:
                yield from _blocks(batch, keep, bounds, n_sub)

    blocks = sent.mapInArrow(pack, PACKED)
    segment, shares, whole = layout.segment if chained else 1, layout.shares, F.lit(0).cast("bigint")
    if spans(window, layout, chained):
        return _by_spans(blocks, layout), closed
    to = lambda sub, op, seg, share: F.struct(seg.cast("bigint").alias("segment"), share.cast("bigint").alias("share"), sub.cast("bigint").alias("sub_id"), F.lit(op).alias("op"))
    in_segment = lambda x: F.floor(x / segment) if segment > 1 else x
    all_shares, inserted = F.sequence(whole, F.lit(shares - 1).cast("bigint")), F.col("first")
    insert = F.transform(all_shares, lambda k: to(inserted, INSERT, in_segment(inserted), k))
    if segment > 1:  # the last subwindows of a segment also warm the next one up
        early = F.transform(all_shares, lambda k: to(inserted, WARM, in_segment(inserted) + 1, k))
        insert = F.when(F.pmod(inserted, F.lit(segment)) >= segment - layout.warm, F.concat(insert, early)).otherwise(insert)
    probe = F.transform(F.sequence("first", "last"), lambda x: to(x, PROBE, in_segment(x), F.pmod("turn", F.lit(shares))))
    return blocks.select("side", F.explode(F.when(F.col("op") == INSERT, insert).otherwise(probe)).alias("to"), "rows").select("side", "to.*", "rows"), closed


def spans(window: win.Window, layout: Layout, chained: bool) -> bool:
    """Are subwindows held span by span?"""
    return window is None and not chained and layout.shares == 1


def _by_spans(blocks: DataFrame, layout: Layout) -> DataFrame:
    """Inserts to their subwindow's span, probes once to each span with a subwindow that they meet.

    Subwindow x belongs to worker x % slots as before, and there to span (x // slots) // reach.
    """
    slots, reach = layout.slots or 1, max(1, SPAN // layout.n_sub)
    segment = F.when(F.col("op") == INSERT, F.array(F.expr(f"first div {slots * reach} * {slots} + first % {slots}"))).otherwise(
        F.filter(F.expr(f"sequence(0L, (last div {slots * reach} + 1) * {slots} - 1)"), lambda g: F.floor(g / slots) * (slots * reach) + g % slots <= F.col("last"))
    )
    sub = F.when(F.col("op") == INSERT, F.col("first")).otherwise(F.col("last") + AFTER)
    return blocks.select("side", F.explode(segment).alias("segment"), F.lit(0).cast("bigint").alias("share"), sub.alias("sub_id"), "op", "rows")


def _blocks(batch: pa.RecordBatch, keep: list[str], bounds: list[str], n_sub: int):
    """Blocks of one Arrow batch: inserts by (side, subwindow), probes by (side, first, last subwindow)."""
    number = lambda c: batch.column(c).to_numpy(zero_copy_only=False)
    is_s, sub, first, last, rank = number("side") == "S", number("sub_id"), number("first__sub"), number("last__sub"), number("rank")
    data = batch.select(keep)
    out: list[list] = [[] for _ in range(6)]

    def add(order: np.ndarray, *keys: np.ndarray, op: int, columns: list[str]) -> None:
        new = np.zeros(len(order), bool)
        for k in keys:
            new[1:] |= k[order][1:] != k[order][:-1]
        for rows in np.split(order, np.flatnonzero(new)):
            r = rows[0]
            side = "S" if is_s[r] == (op == INSERT) else "R"
            block = data.select(columns).take(pa.array(rows))
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, block.schema) as w:
                w.write_batch(block)
            a, b = (sub[r], sub[r]) if op == INSERT else (first[r], last[r])
            for col, x in zip(out, (side, op, int(a), int(b), int(rank[rows].min()) // n_sub, sink.getvalue().to_pybytes()), strict=True):
                col.append(x)

    add(np.lexsort((sub, is_s)), is_s, sub, op=INSERT, columns=[c for c in keep if c not in bounds])
    asking = np.flatnonzero(first <= last)
    if len(asking):
        order = asking[np.lexsort((number("value")[asking], last[asking], first[asking], is_s[asking]))]
        add(order, is_s, first, last, op=PROBE, columns=keep)
    kinds = (pa.string(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary())
    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds, strict=True)], names=[c.split()[0] for c in PACKED.split(", ")])


def run(prepared: DataFrame, pred: Predicate, window: win.Window, layout: Layout, choose: str | Callable[[int], str], result: str = "pairs", extra: tuple[str, ...] = (), n_bat: int = 1, adjust: bool = True, found: bool = False) -> DataFrame:
    """The plan for one result form: pairs, lists (the pairs of a probe in a subwindow as one row), count (per
    probe and subwindow), ranges or profile. With ``found`` a task keeps its empty range records to itself."""
    ship(prepared.sparkSession)
    name = choose if isinstance(choose, str) else None
    chained = name in (None, "splitter", "auto")
    sent, closed = packed(prepared, pred, window, layout, extra, chained)
    rows = place(sent, layout).sortWithinPartitions("side", "segment", "share", "sub_id", "op")
    plan = Plan(window, layout, (lambda _, name=name: name) if name else choose, result, pred.negated, len(closed), closed, extra, n_bat, chained, adjust, found)
    if result == "pairs":
        types = {f.name: f.dataType for f in prepared.schema.fields}
        schema = StructType([StructField(f"{s}_{c}", types[c]) for c in ("key", "value", *extra) for s in "sr"])
        names = [f.name for f in schema.fields]
    else:
        schema = {"lists": LISTS, "count": COUNTS, "ranges": RANGES, "profile": PROFILE}[result]
        names = [c.split()[0] for c in schema.split(", ")]
    work = _work_spans if spans(window, layout, chained) else _work
    return rows.mapInArrow(lambda batches: work(_unpacked(batches), plan, names), schema)


def _unpacked(batches):
    """((side, segment, share, sub_id), op, tuples) of every block."""
    for batch in batches:
        for *where, op, data in zip(*(batch.column(c).to_pylist() for c in ("side", "segment", "share", "sub_id", "op", "rows")), strict=True):
            yield tuple(where), op, pa.ipc.open_stream(pa.py_buffer(data)).read_next_batch()


def chained_splitters(prepared: DataFrame, layout: Layout) -> DataFrame:
    """(side, sub_id, splitters) of every subwindow, each from its predecessor's counts, least and
    greatest values; a task carries on a segment, after ``warm`` subwindows before it."""
    ship(prepared.sparkSession)
    rows = prepared.filter("value is not null")
    segment = F.floor(F.col("sub_id") / layout.segment)
    own = F.struct(segment.alias("segment"), F.lit(INSERT).alias("op"))
    early = F.when(F.pmod("sub_id", F.lit(layout.segment)) >= layout.segment - layout.warm, F.array(F.struct((segment + 1).alias("segment"), F.lit(WARM).alias("op")))).otherwise(F.array().cast("array<struct<segment:bigint,op:int>>"))
    sent = rows.select("side", "sub_id", "value", F.explode(F.concat(F.array(own), early)).alias("to")).select("side", "to.segment", F.lit(0).cast("bigint").alias("share"), "sub_id", "to.op", "value")
    plan = Plan(None, layout, None, "splitters", False, 0, (), (), 1, True)

    def work(batches):
        chain, before = None, None
        for where, op, values in _subwindows(batches):
            if where[:2] != before:
                chain, before = Chain(plan), where[:2]
            if op == INSERT:
                bounds = pa.array([chain.inherited(values).astype(np.int64)], pa.list_(pa.int64()))
                yield pa.RecordBatch.from_arrays([pa.array([where[0]]), pa.array([int(where[3])], pa.int64()), bounds], names=["side", "sub_id", "splitters"])
            chain.adjust(values)

    return sent.repartition("side", "segment").sortWithinPartitions("side", "segment", "sub_id").mapInArrow(work, "side string, sub_id bigint, splitters array<bigint>")


def _subwindows(batches):
    """(address, op, all values) of one subwindow after the other."""
    now, held = None, []
    for where, op, rows in _pieces(batches):
        if (where, op) != now:
            if held:
                yield *now, np.concatenate(held)
            now, held = (where, op), []
        held.append(rows.column("value").to_numpy())
    if held:
        yield *now, np.concatenate(held)


# -- in a task ---------------------------------------------------------------------------------


def _pieces(batches: Iterator[pa.RecordBatch]):
    """Runs of rows of one address: ((side, segment, share, sub_id), op, rows)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [batch.column(c).to_numpy(zero_copy_only=False) for c in ("side", "segment", "share", "sub_id", "op")]
        new = np.zeros(batch.num_rows, bool)
        for c in cols:
            new[1:] |= c[1:] != c[:-1]
        at = np.append(np.flatnonzero(np.concatenate(([True], new[1:]))), batch.num_rows)
        for a, b in zip(at[:-1], at[1:], strict=True):
            yield tuple(c[a] for c in cols[:4]), int(cols[4][a]), batch.slice(a, b - a)


def _work(pieces, plan: Plan, names: list[str]) -> Iterator[pa.RecordBatch]:
    chain = Chain(plan)
    now, held, early, sub = None, [], [], None
    for where, op, rows in pieces:
        if where != now:
            if early:
                chain.warm(in_arrival_order(early).column("value").to_numpy())
            if sub is None and held:
                sub = Subwindow(now, held, chain, plan)
            if sub is not None:
                yield from sub.finish(names)
            if now is None or where[:3] != now[:3]:
                chain = Chain(plan)
            now, held, early, sub = where, [], [], None
        if op == WARM:
            early.append(rows)
        elif op == INSERT:
            held.append(rows)
        else:
            if sub is None and held:
                sub = Subwindow(now, held, chain, plan)
            if sub is not None:  # a subwindow without tuples has nothing to say
                yield from sub.answer(rows, names)
    if sub is None and held:
        sub = Subwindow(now, held, chain, plan)
    if sub is not None:
        yield from sub.finish(names)


def _work_spans(pieces, plan: Plan, names: list[str]) -> Iterator[pa.RecordBatch]:
    """Span after span: its subwindows are built, then probes pass by them in slices."""
    for _, found in groupby(pieces, key=lambda piece: piece[0][:3]):
        held: dict[tuple, list] = {}
        subs: list[Subwindow] = []
        asked, lasts, n = [], [], 0
        for where, op, rows in found:
            if op == INSERT:
                held.setdefault(where, []).append(rows)
                continue
            if held:  # the first probes: all inserts are there
                subs, held = [Subwindow(at, tuples, Chain(plan), plan) for at, tuples in held.items()], {}
            asked.append(rows)
            lasts.append(np.full(rows.num_rows, where[3] - AFTER))
            n += rows.num_rows
            if n >= PROBES:
                yield from _pass_by(subs, asked, lasts, names)
                asked, lasts, n = [], [], 0
        subs = subs or [Subwindow(at, tuples, Chain(plan), plan) for at, tuples in held.items()]
        if asked:
            yield from _pass_by(subs, asked, lasts, names)
        for sub in subs:
            yield from sub.finish(names)


def _pass_by(subs: list[Subwindow], asked: list[pa.RecordBatch], lasts: list[np.ndarray], names: list[str]) -> Iterator[pa.RecordBatch]:
    """Probes in the order of the last subwindow that they meet, against each subwindow."""
    rows, last = pa.concat_batches(asked), np.concatenate(lasts)
    near = Near.of(rows, subs[0].plan) if subs else None
    for sub in subs:
        first = int(np.searchsorted(last, sub.sub_id))
        if first == rows.num_rows:
            continue
        if near is None or sub.buffer is not None:
            yield from sub.answer(rows.slice(first), names)
            continue
        some = near.to(sub.distinct)
        some = some[some >= first]
        if len(some):
            yield from sub.answer(rows.take(pa.array(some)), names)


class Near:
    """Probes in the order of their bounds: a subwindow's few values then find the probes that ask for
    one of them, and the others, most of them if the band is narrow, are not looked at."""

    def __init__(self, bands: list[tuple[np.ndarray, np.ndarray, np.ndarray]]):
        self.bands = bands

    @staticmethod
    def of(rows: pa.RecordBatch, plan: Plan) -> Near | None:
        """None where a probe without a match has a row too, or where bounds are open or do not rise together."""
        if plan.negated or not (plan.result in ("pairs", "lists", "count") or (plan.result == "ranges" and plan.found)):
            return None
        bands = []
        for k in range(plan.bands):
            if not {f"lo{k}", f"hi{k}"} <= set(rows.schema.names) or rows.column(f"lo{k}").null_count or rows.column(f"hi{k}").null_count:
                return None
            lo, hi = (rows.column(f"{end}{k}").to_numpy(zero_copy_only=False) for end in ("lo", "hi"))
            order = np.argsort(lo, kind="stable")
            lo, hi = lo[order], hi[order]
            if (hi[1:] < hi[:-1]).any():
                return None
            bands.append((order, lo, hi))
        return Near(bands)

    def to(self, values: np.ndarray) -> np.ndarray:
        """Places of the probes with one of the values (in rising order) inside their bounds."""
        found = []
        for order, lo, hi in self.bands:
            first, last = np.searchsorted(hi, values, "left"), np.searchsorted(lo, values, "right")
            if len(values) > 1:  # both rise: what a value shares with the one before is left to that
                first[1:] = np.maximum(first[1:], last[:-1])
            n = np.maximum(last - first, 0)
            found.append(order[st.spans(first, n)[1]])
        return np.sort(found[0]) if len(found) == 1 else np.unique(np.concatenate(found))


def in_arrival_order(held: list[pa.RecordBatch]) -> pa.Table:
    """One subwindow's tuples from its blocks."""
    table = pa.Table.from_batches(held).combine_chunks()
    done, rank = table.column("done").to_numpy(), table.column("rank").to_numpy()
    if len(held) == 1 and (np.diff(rank) > 0).all() and (np.diff(done) >= 0).all():
        return table
    return table.take(pa.array(np.lexsort((rank, done))))


class Chain:
    """What a subwindow hands to its successor: boundaries, and facts for the choice of a structure."""

    def __init__(self, plan: Plan):
        self.plan, self.bounds, self.range = plan, None, None
        self.parts: list[np.ndarray] = []
        self.rising = self.drift = self.selectivity = None

    def warm(self, values: np.ndarray) -> None:
        """A subwindow of the segment before: one round of adjustment and its facts."""
        self.adjust(values)
        self.learn(values, 0, 0)

    def inherited(self, values: np.ndarray) -> np.ndarray:
        if self.bounds is None:
            layout = self.plan.layout
            self.bounds = st.equal_widths(values, layout.partitions, layout.lowest, layout.highest)
        return self.bounds

    def adjust(self, values: np.ndarray) -> None:
        if self.plan.adjust:
            self.bounds = st.adjusted(values, self.inherited(values))

    def kind(self, sub_id: int, values: np.ndarray) -> str:
        kind = self.plan.choose(sub_id)
        if kind != "auto":
            return kind
        if self.plan.result in ("count", "ranges") or self.plan.negated:
            return "sorted"
        if self.drift is None:
            return "wideleaf"  # no predecessor to learn from
        return choose_index(self.plan.n_bat, self.selectivity or 0, self.drift, self.rising >= 0.9)

    def learn(self, values: np.ndarray, matches: int, whole_probes: int) -> None:
        """Facts of this subwindow (arrival order) for the choice of the next."""
        if len(values) > 1:
            self.rising = float(np.mean(values[1:] >= values[:-1]))
        if self.range is not None:
            self.drift = float(np.mean((values < self.range[0]) | (values > self.range[1])))
        self.range = (values.min(), values.max())
        self.selectivity = matches / whole_probes if whole_probes else 0


class Subwindow:
    """One subwindow's tuples under their structure, and its answers."""

    def __init__(self, where: tuple, held: list[pa.RecordBatch], chain: Chain, plan: Plan):
        self.side, self.sub_id, self.plan, self.chain = where[0], int(where[3]), plan, chain
        table = in_arrival_order(held)
        self.buffer = None
        if "late" in table.column_names:  # late tuples stay beside the structure and are scanned
            late = table.column("late")
            self.buffer = Tuples(table.filter(late), plan) if pa.compute.any(late).as_py() else None
            table = table.filter(pa.compute.invert(late))
        values = table.column("value").to_numpy()
        self.kind = chain.kind(self.sub_id, values) if len(values) else "sorted"
        self.arrival_values = values
        self._distinct = None
        if self.kind == "sorted":
            order = np.argsort(values, kind="stable")
            self.index = st.SortedRun(values[order], plan.layout.partitions)
        else:
            if self.kind == "splitter":
                bounds = chain.inherited(values)
            elif self.kind == "wideleaf":
                bounds = st.leaf_bounds(values, max(1, -(-plan.layout.n_sub // plan.layout.partitions)), max(256, len(values) // 8))
            else:
                raise ValueError(self.kind)
            self.index = st.Partitions(values, bounds, self.kind)
            order = self.index.order
        self.main = Tuples(table.take(pa.array(order)), plan)
        self.probes = self.whole = self.matched = self.whole_matched = self.late_touched = 0
        self.arrivals = None

    @property
    def distinct(self) -> np.ndarray:
        """Its values once, in order."""
        if self._distinct is None:
            self._distinct = np.unique(self.arrival_values)
        return self._distinct

    # bounds of a batch of probes as (numbers, which are closed off)
    def _bounds(self, rows: pa.RecordBatch, band: int):
        n = rows.num_rows
        probe_is_s = self.side == "R"
        lo_s, lo_r, hi_s, hi_r = self.plan.closed[band]
        out = []
        for end in ("lo", "hi"):
            name = f"{end}{band}"
            if name in rows.schema.names:
                col = rows.column(name)
                mask = ~np.asarray(col.is_null()) if col.null_count else np.ones(n, bool)
                known = (col.fill_null(0) if col.null_count else col).to_numpy(zero_copy_only=False)
            else:
                known, mask = np.zeros(n, np.int64), np.zeros(n, bool)
            out.append((known, mask))
        lo_closed = np.full(n, lo_s if probe_is_s else lo_r)
        hi_closed = np.full(n, hi_s if probe_is_s else hi_r)
        return out[0], out[1], lo_closed, hi_closed

    def answer(self, rows: pa.RecordBatch, names: list[str]) -> Iterator[pa.RecordBatch]:
        asked = Tuples(rows, self.plan)
        self.probes += rows.num_rows
        whole = self.main.whole_for(asked)
        self.whole += int(whole.sum())
        form = self.plan.result
        if form in ("pairs", "lists") or (form == "profile" and self.kind != "sorted"):
            for probe, place in self._pairs(rows, asked, whole):
                self.matched += len(probe)
                self.whole_matched += int(whole[probe].sum())
                if form != "profile" and len(probe):
                    yield self._found(rows, probe, self.main, place, names)
        else:
            yield from self._by_ranges(rows, asked, whole, names)
        if self.buffer is not None:
            yield from self._scan_buffer(rows, asked, names)

    def _pairs(self, rows: pa.RecordBatch, asked: Tuples, whole: np.ndarray):
        """(probe, place) of every match, in bounded slices."""
        for band in range(self.plan.bands):
            lo, hi, lc, hc = self._bounds(rows, band)
            if self.kind == "sorted":
                start, end = self.index.ranges(lo, hi, lc, hc)
                ranges = [(np.zeros(len(start), np.int64), start), (end, np.full(len(start), self.main.n))] if self.plan.negated else [(start, end)]
                for a_, b_ in ranges:
                    n = b_ - a_
                    for a, b in st.slices(n, AT_ONCE):
                        probe, place = st.spans(a_[a:b], n[a:b])
                        yield self._still(asked, probe + a, place, whole)
            elif self.plan.negated:  # equality, then everything else
                for side in ("lo", "hi"):
                    low = (lo, (hi[0], np.zeros(len(hi[0]), bool))) if side == "hi" else ((lo[0], np.zeros(len(lo[0]), bool)), lo)
                    ends = (np.zeros(len(lc), bool), np.zeros(len(hc), bool))
                    for probe, place in self.index.matches(*low, *ends, AT_ONCE):
                        yield self._still(asked, probe, place, whole)
            else:
                for probe, place in self.index.matches(lo, hi, lc, hc, AT_ONCE):
                    yield self._still(asked, probe, place, whole)

    def _still(self, asked: Tuples, probe: np.ndarray, place: np.ndarray, whole: np.ndarray):
        """Pairs whose stored tuple was there before the probe and has not left the window."""
        keep = whole[probe]
        test = np.flatnonzero(~keep)
        if len(test):
            keep = keep.copy()
            keep[test] = self.main.met(place[test], asked, probe[test])
            probe, place = probe[keep], place[keep]
        return probe, place

    def _by_ranges(self, rows, asked, whole, names):
        """Range records, or their sizes: border probes count by value and arrival."""
        form, total = self.plan.result, np.zeros(rows.num_rows, np.int64)
        if self.arrivals is None:
            self.arrivals = Arrivals(self.main)
        sparse = form == "ranges" and self.plan.found and not self.plan.negated
        first, last = (None, None) if sparse else self.arrivals.limits(asked)
        for band in range(self.plan.bands):
            lo, hi, lc, hc = self._bounds(rows, band)
            start, end = self.index.ranges(lo, hi, lc, hc)
            if sparse:
                some = np.flatnonzero(end > start)
                if len(some):
                    keys, n = rows.column("key").take(pa.array(some)), len(some)
                    ranks = self.arrivals.ranks(*self.arrivals.limits(Tuples(rows.take(pa.array(some)), self.plan)))
                    yield _batch(names, np.full(n, "S" if self.side == "R" else "R"), keys, np.full(n, self.sub_id), np.full(n, band, np.int32), start[some], end[some], np.zeros(n, bool), *ranks)
                continue
            if form == "ranges":
                yield _batch(names, np.full(rows.num_rows, "S" if self.side == "R" else "R"), rows.column("key"), np.full(rows.num_rows, self.sub_id), np.full(rows.num_rows, band, np.int32), start, end, np.full(rows.num_rows, self.plan.negated), *self.arrivals.ranks(first, last))
                continue
            n = end - start
            border = np.flatnonzero(~whole)
            if len(border):
                n[border] = self.arrivals.count(start[border], end[border], first[border], last[border], asked, border, self.main)
            if self.plan.negated:
                everything = np.full(rows.num_rows, self.main.n)
                if len(border):
                    zero = np.zeros(len(border), np.int64)
                    everything[border] = self.arrivals.count(zero, zero + self.main.n, first[border], last[border], asked, border, self.main)
                n = everything - n
            total += n
        if form == "ranges":
            return
        self.matched += int(total.sum())
        self.whole_matched += int(total[whole].sum())
        some = total > 0
        if form == "count" and some.any():
            yield _batch(names, np.full(int(some.sum()), "S" if self.side == "R" else "R"), rows.column("key").filter(pa.array(some)), total[some])

    def _scan_buffer(self, rows, asked, names):
        """Late tuples: each is compared with every probe of the batch."""
        form, b = self.plan.result, self.buffer
        total = np.zeros(rows.num_rows, np.int64)
        for band in range(self.plan.bands):
            lo, hi, lc, hc = self._bounds(rows, band)
            for at in range(0, rows.num_rows, max(1, AT_ONCE // b.n)):
                probes = np.arange(at, min(rows.num_rows, at + max(1, AT_ONCE // b.n)))
                probe, place = np.repeat(probes, b.n), np.tile(np.arange(b.n), len(probes))
                self.late_touched += len(probe)
                hit = st.within(b.value[place], probe, lo, lc, "lo") & st.within(b.value[place], probe, hi, hc, "hi")
                hit = (hit != self.plan.negated) & b.met(place, asked, probe)
                probe, place = probe[hit], place[hit]
                self.matched += len(probe)
                np.add.at(total, probe, 1)
                if form in ("pairs", "lists") and len(probe):
                    yield self._found(rows, probe, b, place, names)
        some = total > 0
        if form == "ranges" and b.n:
            raise ValueError("range records are of the sorted run alone; ask for counts or pairs when tuples are late")
        if form == "count" and some.any():
            yield _batch(names, np.full(int(some.sum()), "S" if self.side == "R" else "R"), rows.column("key").filter(pa.array(some)), total[some])

    def _found(self, rows, probe, held: Tuples, place, names) -> pa.RecordBatch:
        if self.plan.result == "pairs":
            return self._pair_batch(rows, probe, held, place, names)
        if (np.diff(probe) < 0).any():
            order = np.argsort(probe, kind="stable")
            probe, place = probe[order], place[order]
        start = np.append(np.flatnonzero(np.diff(probe, prepend=-1)), len(probe))
        keys = pa.ListArray.from_arrays(pa.array(start, pa.int32()), held.column("key").take(pa.array(place)))
        return _batch(names, np.full(len(keys), "S" if self.side == "R" else "R"), rows.column("key").take(pa.array(probe[start[:-1]])), keys)

    def _pair_batch(self, rows, probe, held: Tuples, place, names) -> pa.RecordBatch:
        probe, place = pa.array(probe), pa.array(place)
        cols = []
        for c in ("key", "value", *self.plan.extra):
            asked, stored = rows.column(c).take(probe), held.column(c).take(place)
            cols += [asked, stored] if self.side == "R" else [stored, asked]
        return pa.RecordBatch.from_arrays(cols, names=names)

    def finish(self, names: list[str]) -> Iterator[pa.RecordBatch]:
        """Hands on to the successor; the profile row."""
        if len(self.arrival_values) and self.plan.chained:
            self.chain.adjust(self.arrival_values)
            self.chain.learn(self.arrival_values, self.whole_matched, self.whole)
        if self.plan.result == "profile":
            sizes = self.index.sizes
            n, p = self.main.n, max(1, len(sizes))
            mae = float(np.abs(sizes * p - n).sum() / (n * p)) if n else 0.0
            yield _batch(names, *([x] for x in (self.side, self.sub_id, self.kind, n + (self.buffer.n if self.buffer else 0), self.probes, self.whole, self.index.touched, self.index.copied, self.late_touched, self.matched)), np.array([p], np.int32), [int(sizes.max()) if len(sizes) else 0], [round(mae, 6)])


def _batch(names: list[str], *cols) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c) for c in cols], names=names)


class Tuples:
    """Columns of stored or probing tuples as arrays."""

    def __init__(self, rows: pa.RecordBatch | pa.Table, plan: Plan):
        self.n, self.plan = rows.num_rows, plan
        self.rows = rows
        number = lambda c: self.column(c).to_numpy(zero_copy_only=False)
        self.value, self.rank, self.done, self.opp = number("value"), number("rank"), number("done"), number("opp")
        self.us = number("us") if "us" in rows.schema.names else None
        if self.n:
            self.last_done, self.first_rank = self.done.max(), self.rank.min()
            if self.us is not None:
                self.oldest, self.newest = self.us.min(), self.us.max()

    def column(self, name: str) -> pa.Array:
        col = self.rows.column(name)
        return (col.combine_chunks() if col.num_chunks != 1 else col.chunk(0)) if isinstance(col, pa.ChunkedArray) else col

    def whole_for(self, asked: Tuples) -> np.ndarray:
        """Is every tuple here in the probe's window? From oldest and newest alone."""
        if not self.n:
            return np.zeros(asked.n, bool)
        return self._met(self.last_done, self.first_rank, self.oldest if self.us is not None else None, self.newest if self.us is not None else None, asked, slice(None))

    def met(self, place: np.ndarray, asked: Tuples, probe: np.ndarray) -> np.ndarray:
        us = self.us[place] if self.us is not None else None
        return self._met(self.done[place], self.rank[place], us, us, asked, probe)

    def _met(self, done, rank, oldest, newest, asked: Tuples, probe) -> np.ndarray:
        window = self.plan.window
        met = asked.done[probe] > done
        if isinstance(window, CountWindow) and window.exact:
            met &= asked.opp[probe] - rank < window.size
        if isinstance(window, TimeWindow) and window.exact:
            reach = window.seconds * 1_000_000
            met &= (asked.us[probe] - oldest <= reach) & (newest - asked.us[probe] <= reach)
        return met


class Arrivals:
    """The window's part of a count: which arrival numbers of a subwindow a probe may meet."""

    def __init__(self, held: Tuples):
        by = np.lexsort((held.rank, held.done))
        self.done, self.rank = held.done[by], held.rank[by]
        self.us = held.us[by] if held.us is not None else None
        self.in_order = self.us is None or bool(np.all(self.us[1:] >= self.us[:-1]))
        self.ranked = bool(np.all(self.rank[1:] >= self.rank[:-1]))
        self.number = np.empty(held.n, np.int64)
        self.number[by] = np.arange(held.n)
        self.plan, self.counts = held.plan, None

    def limits(self, asked: Tuples) -> tuple[np.ndarray, np.ndarray]:
        """First and past-last arrival number, where one run of numbers says it all."""
        window = self.plan.window
        last = np.searchsorted(self.done, asked.done, side="left")
        first = np.zeros(asked.n, np.int64)
        if isinstance(window, CountWindow) and window.exact:
            first = np.searchsorted(self.rank, asked.opp - window.size, side="right")
        if isinstance(window, TimeWindow) and window.exact and self.in_order:
            reach = window.seconds * 1_000_000
            first = np.searchsorted(self.us, asked.us - reach, side="left")
            last = np.minimum(last, np.searchsorted(self.us, asked.us + reach, side="right"))
        return first, np.maximum(first, last)

    def ranks(self, first: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The same as ranks of the side: [from, to)."""
        edge = np.append(self.rank, self.rank[-1] + 1 if len(self.rank) else 0)
        return edge[first], np.where(last > first, edge[np.maximum(last, 1) - 1] + 1, edge[first])

    def count(self, start, end, first, last, asked: Tuples, rows: np.ndarray, held: Tuples) -> np.ndarray:
        """Places of [start, end) within the arrival numbers; out-of-order times are compared one by one."""
        if self.in_order:
            if self.counts is None:
                self.counts = st.ArrivalCounts(self.number)
            return self.counts.before(start, end, last) - self.counts.before(start, end, first)
        out = np.zeros(len(start), np.int64)
        n = end - start
        for a, b in st.slices(n, AT_ONCE):
            probe, place = st.spans(start[a:b], n[a:b])
            np.add.at(out, a + probe[held.met(place, asked, rows[a + probe])], 1)
        return out
