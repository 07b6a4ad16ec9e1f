"""Harmonic packing of token sequences, each worker for itself.

Sequences hold ``capacity`` tokens. A document is cut into pieces whose lengths are
reciprocals of the capacity: whole sequences first, then capacity/2, /4, ... down to
``least`` tokens; what is left is shorter than ``least``. Piece lengths fall into
harmonic classes (class k: capacity/(k+1) < length <= capacity/k) and a bin of class k
takes exactly k pieces, so a worker fills the bins of each class without looking at
another. Pieces cut to capacity/k fill their bins exactly. What a worker has in bins
that are not full when its rows end is laid end to end and cut again at the capacity, so
a worker pads one sequence at most for these, and the short classes at most 1/(k+1).

Decisions depend on the rows of a partition and their order alone, so a task that runs
again gives the same rows. ``sequence_id`` is the partition number times 2**40 plus a
counter.

Defined cases: a null text is empty and packs its end id; repeated doc_ids are separate
documents; an empty table gives no pieces; extra columns are not read. There is no
longest text: pieces are made from a document's length alone.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from windowjoin.llm import common
from windowjoin.llm.word_tokens import encoded

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
NAMES = [c.split()[0] for c in SCHEMA.split(", ")]
WORKER = 1 << 40


def piece_lengths(n: int, capacity: int = 2048, least: int = 64) -> list[int]:
    """Cut n tokens into harmonic pieces: exact reciprocals, then one short rest."""
    out = [capacity] * (n // capacity)
    rest, size = n % capacity, capacity // 2
    while rest >= least and size >= least:
        if rest >= size:
            out.append(size)
            rest -= size
        size //= 2
    if rest:
        out.append(rest)
    return out


class HarmonicPacker:
    """Bins of k pieces for class k; ``add`` returns the pieces of a bin that got full."""

    def __init__(self, capacity: int = 2048):
        self.capacity = capacity
        self.open: dict[int, list[tuple]] = {}
        self.bins = 0

    def _close(self, pieces: list[tuple]) -> list[tuple]:
        out, offset = [], 0
        for p in pieces:
            out.append((*p, self.bins, offset))
            offset += p[2]
        self.bins += 1
        return out

    def add(self, doc: object, start: int, length: int, ids: np.ndarray, doc_tokens: int) -> list[tuple]:
        k = self.capacity // length
        bin_ = self.open.setdefault(k, [])
        bin_.append((doc, start, length, ids, doc_tokens))
        if len(bin_) < k:
            return []
        del self.open[k]
        return self._close(bin_)

    def finish(self) -> list[tuple]:
        """Pieces of the bins still open, end to end, cut at the capacity."""
        out, now, room = [], [], self.capacity
        for k in sorted(self.open):
            for doc, start, length, ids, total in self.open[k]:
                while length:
                    take = min(room, length)
                    now.append((doc, start, take, ids[:take], total))
                    start, length, ids, room = start + take, length - take, ids[take:], room - take
                    if not room:
                        out += self._close(now)
                        now, room = [], self.capacity
        self.open.clear()
        return out + (self._close(now) if now else [])


def pack(docs: DataFrame, definition: str, capacity: int = 2048, end_id: int = 1, least: int = 64) -> DataFrame:
    """One row per piece of ``docs`` (doc_id, text); no exchange is needed."""
    spark = docs.sparkSession
    common.ship(spark)
    shared = spark.sparkContext.broadcast(definition)

    def table(pieces: list[tuple], worker: int) -> pa.RecordBatch:
        cols = list(zip(*pieces, strict=True))
        crc = [zlib.crc32(ids.tobytes()) for ids in cols[3]]
        seq = np.array(cols[5], np.int64) + worker * WORKER
        return pa.RecordBatch.from_arrays(
            [pa.array(cols[0], pa.int64()), *(pa.array(c, pa.int64()) for c in (cols[1], cols[2], crc, cols[4])), pa.array(seq), pa.array(cols[6], pa.int64())], names=NAMES
        )

    def rows(batches):
        packer, worker = HarmonicPacker(capacity), common.task_partition()
        for keys, ids, counts in encoded(batches, shared.value, end_id):
            ids = ids.astype("<u4", copy=False)
            done: list[tuple] = []
            at = 0
            for doc, n in zip(keys.to_pylist(), counts.tolist(), strict=True):
                start = 0
                for length in piece_lengths(n, capacity, least):
                    # a piece kept in an open bin owns its ids, not the whole slice
                    own = ids[at + start : at + start + length]
                    done += packer.add(doc, start, length, own if length == capacity else own.copy(), n)
                    start += length
                at += n
            if done:
                yield table(done, worker)
        if rest := packer.finish():
            yield table(rest, worker)

    return common.texts(docs, "doc_id").mapInArrow(rows, SCHEMA)
