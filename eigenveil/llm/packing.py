"""Packing documents into fixed-length sequences by best fit and swap-based local search.

Documents become pieces (only those over the limit are cut; the first piece takes the
remainder), pieces are dealt to groups of bounded size by a hash, and each group is
packed on its own: best fit over decreasing lengths, then a local search over all
underfull bins that empties the least filled ones by moves, one-for-one and two-for-one
exchanges, each of which raises the sum of squared fills, until none gains.  Null texts are empty documents (their end id alone),
repeated rows are packed as often as they stand there, an empty table gives no rows.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise
from .tokens import encoder, in_chunks

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def cut_points(length: int, limit: int) -> list[tuple[int, int]]:
    """(start, length) of each piece; all but the first are of the full limit."""
    first = length if length <= limit else length % limit or limit
    return [(0, first), *((at, limit) for at in range(first, length, limit))]


def pieces(docs: DataFrame, vocabulary: str, limit: int = 2048, end_id: int = 0, with_ids: bool = False) -> DataFrame:
    """Encode whole texts, append ``end_id`` and cut; ``with_ids`` adds the ids of each piece."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start, texts in in_chunks(batch.column("text")):
                ids = batch.column("doc_id").slice(start, len(texts)).to_pylist()
                rows: list[list] = [[] for _ in range(6)]
                for doc_id, got in zip(ids, encoder(vocabulary).encode(texts)):
                    got += end_id.to_bytes(4, "little")
                    for k, (s, n) in enumerate(cut_points(len(got) // 4, limit)):
                        part = got[4 * s : 4 * (s + n)]
                        for column, value in zip(rows, (doc_id, k, s, n, zlib.crc32(part), part)):
                            column.append(value)
                columns = [pa.array(rows[0], pa.int64()), pa.array(rows[1], pa.int32()), *(pa.array(x, pa.int64()) for x in rows[2:5])]
                names = ["doc_id", "piece", "start", "length", "ids_crc32"]
                if with_ids:
                    columns.append(pa.array([np.frombuffer(x, np.uint32).tolist() for x in rows[5]], pa.list_(pa.int64())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(cut, PIECES + (", ids array<long>" if with_ids else ""))


def best_fit(lengths: np.ndarray, limit: int) -> list[list[int]]:
    """Bins of item numbers: longest first, each into the fullest bin that still takes it."""
    bins: list[list[int]] = []
    rooms: dict[int, list[int]] = {}
    open_rooms: list[int] = []
    for i in np.argsort(-lengths, kind="stable").tolist():
        n = int(lengths[i])
        at = bisect_left(open_rooms, n)
        if at < len(open_rooms):
            room = open_rooms[at]
            b = rooms[room].pop()
            if not rooms[room]:
                del rooms[room]
                open_rooms.pop(at)
            bins[b].append(i)
            room -= n
        else:
            b, room = len(bins), limit - n
            bins.append([i])
        if room:
            if room not in rooms:
                rooms[room] = []
                insort(open_rooms, room)
            rooms[room].append(b)
    return bins


def _returns(items: tuple[int, ...]) -> list[int]:
    """The lengths that a bin can give back for one item taken: none, one item's, two items'."""
    sizes = sorted(set(items))
    twice = {n for n, m in zip(items, items[1:]) if n == m}
    pairs = {a + b for k, a in enumerate(sizes) for b in sizes[k + 1 :]} | {2 * n for n in twice}
    return sorted({0, *sizes} | pairs)


class _Partners:
    """Distinct compositions (sorted item lengths) of underfull bins, by what they can give back and by room."""

    def __init__(self, limit: int):
        self.limit, self.count = limit, Counter()
        self.holders: list[list[tuple[int, tuple[int, ...]]]] = [[] for _ in range(limit + 1)]
        #: the greatest room among the bins that can give back so much, and -1 without any
        self.room = np.full(limit + 1, -1, np.int64)

    def add(self, items: tuple[int, ...]) -> None:
        self.count[items] += 1
        if self.count[items] == 1:
            entry = (self.limit - sum(items), items)
            for back in _returns(items):
                insort(self.holders[back], entry)
                self.room[back] = self.holders[back][-1][0]

    def remove(self, items: tuple[int, ...]) -> None:
        self.count[items] -= 1
        if not self.count[items]:
            del self.count[items]
            entry = (self.limit - sum(items), items)
            for back in _returns(items):
                held = self.holders[back]
                held.pop(bisect_left(held, entry))
                self.room[back] = held[-1][0] if held else -1

    def best(self, source: tuple[int, ...]) -> tuple[int, int, tuple[int, ...]] | None:
        """(item, length given back, partner) of the greatest gain that raises the sum of squared fills."""
        room, found, most = self.limit - sum(source), None, 0
        for n in sorted(set(source), reverse=True):
            if n <= most:
                break
            for back in np.flatnonzero(self.room[: n - most] >= n - np.arange(n - most)).tolist():
                # the fullest bin that takes the gain; it must end up fuller than the source was
                gain, held = n - back, self.holders[back]
                least, items = held[bisect_left(held, (gain,))]
                if least < room + gain:
                    found, most = (n, back, items), gain
                    break
        return found


def _without(items: tuple[int, ...], back: int) -> tuple[list[int], list[int]]:
    """What stays and what is given back, of ``back`` in all: nothing, one item or two."""
    left = list(items)
    if not back:
        return left, []
    if back in left:
        left.remove(back)
        return left, [back]
    number = Counter(items)
    one = next(n for n in left if (number[back - n] > 1 if back - n == n else back - n in number))
    left.remove(one)
    left.remove(back - one)
    return left, [one, back - one]


def local_search(bins: list[list[int]], lengths: np.ndarray, limit: int) -> list[list[int]]:
    """Empty underfull bins by moves and exchanges that raise the sum of squared fills.

    The least filled bins give first, and all other underfull bins can take: a move puts
    an item into a partner's room; an exchange puts a longer item there and takes back one
    shorter item, or two that are shorter together.  Bins with items of equal lengths are
    tried once.  This goes on until no step gains anywhere, or until the bins are as few
    as the total length allows.
    """
    length = lengths.tolist()
    fill = [sum(length[i] for i in b) for b in bins]
    spare = sum(limit - n for n in fill)
    if spare < limit:
        return [b for b in bins if b]
    under = [b for b, n in zip(bins, fill) if 0 < n < limit]
    done = [b for b, n in zip(bins, fill) if b and not 0 < n < limit]
    partners, full = _Partners(limit), []
    for b in under:
        partners.add(tuple(sorted(length[i] for i in b)))
    gained = True
    while gained and spare >= limit:
        gained = False
        for first in sorted(partners.count, key=lambda x: (sum(x), x)):
            while first in partners.count and spare >= limit:
                source = first
                partners.remove(source)
                while source and (step := partners.best(source)):
                    item, back, target = step
                    partners.remove(target)
                    stays, given = _without(target, back)
                    taken = tuple(sorted([*stays, item]))
                    if sum(taken) < limit:
                        partners.add(taken)
                    else:
                        full.append(taken)
                    rest = list(source)
                    rest.remove(item)
                    source = tuple(sorted([*rest, *given]))
                if source:
                    partners.add(source)
                else:
                    spare -= limit
                if source == first:
                    break
                gained = True
    # items of one length are alike: hand them out to the compositions found
    pool: dict[int, list[int]] = {}
    for b in reversed(under):
        for i in reversed(b):
            pool.setdefault(length[i], []).append(i)
    found = full + [x for x in sorted(partners.count, reverse=True) for _ in range(partners.count[x])]
    return done + [[pool[n].pop() for n in reversed(x)] for x in found]


def pack(lengths: np.ndarray, limit: int) -> list[list[int]]:
    return local_search(best_fit(lengths, limit), lengths, limit)


def packed(cut: DataFrame, limit: int = 2048, group_pieces: int = 60_000) -> DataFrame:
    """Add sequence_id and offset to pieces; a group holds about ``group_pieces`` pieces."""
    groups = max(1, -(-cut.count() // group_pieces))
    names = [f"{n} {t}" for n, t in cut.dtypes]

    def place(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values(["length", "doc_id", "piece"], ignore_index=True, na_position="first")
        lengths = part["length"].to_numpy(np.int64)
        sequence, offset = np.empty(len(part), np.int64), np.empty(len(part), np.int64)
        base = int(part["pack_group"].iloc[0]) << 32
        for b, items in enumerate(pack(lengths, limit)):
            sequence[items] = base + b
            offset[items] = np.cumsum(lengths[items]) - lengths[items]
        return part.drop(columns="pack_group").assign(sequence_id=sequence, offset=offset)

    grouped = cut.withColumn("pack_group", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(groups)))
    return grouped.groupBy("pack_group").applyInPandas(place, ", ".join([*names, "sequence_id long", "offset long"]))


def pack_documents(docs: DataFrame, vocabulary: str, limit: int = 2048, end_id: int = 0) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    return packed(materialise(pieces(docs, vocabulary, limit, end_id), "pieces"), limit)
