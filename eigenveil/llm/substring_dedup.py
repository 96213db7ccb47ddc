"""Removal of repeated word passages by FM-index shards.

Words are runs of characters other than ASCII white space.  A window is ``window``
consecutive words of one document; a word is removed if it lies in a window that also
starts in a document with a smaller doc_id, judged on the texts as they came.

1. Every window is named by its minimiser, the least hash among its 5-word runs, so
   equal windows have equal minimisers in whatever document they stand.  Minimisers
   that stand in two documents or more are found by hash shards of packed blocks.  A
   block sends a minimiser with its documents while these are ``few``; beyond that it
   sends the minimiser alone and tells its documents itself, as a minimiser of so many
   documents is shared and warm.  So are documents found whose whole word sequence an
   earlier document has: of these all words go, and they need no search.
2. Documents meet their shared minimisers in buckets of ids.  Consecutive windows with one
   shared minimiser form a passage (or several, of two window lengths at most, that
   overlap), which goes to the shard of that minimiser; where a minimiser is warm (held
   by more than ``hot`` documents, or ``few`` of one block), its windows go one by one to
   the shards of their own hashes, so that contexts of a frequent passage do not meet in
   one place.  A bucket sends each passage once, with the places in its smallest document;
   what later documents of the bucket repeat is known to go without a search.
3. Each shard builds an FM-index of its distinct passages: the wavelet matrix of their
   Burrows-Wheeler transform and, in suffix order, the smallest document of each passage.
   All passages are then streamed through backward search, which gives the matching
   statistic at every position; positions at which it reaches the threshold report the
   smallest document among the occurrences, to be compared with the place's own.
4. The intervals found return to their documents, which drop the covered words.

All windows of all documents take part and nothing is capped; words are compared by
64-bit hashes.  Documents with a null text have no words; a null doc_id takes no part
and keeps its words; rows that share a doc_id are one document and remove nothing from
each other; texts in which nothing repeats stay as they are.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordHashes, byte_texts, materialise, mixed, trim, window_hashes
from .fm_index import FmIndex

WINDOW, RUN, HOT, FEW = 13, 5, 64, 8
#: Bytes of text for which one shard is planned.
SHARD_BYTES = 8 << 20
_BLOCK_WORDS = 2_000_000


def sliding_least(values: np.ndarray, width: int) -> np.ndarray:
    """The least of each ``width`` consecutive values."""
    done = 1
    while done < width and len(values):
        step = min(done, width - done)
        values = np.minimum(values[: max(0, len(values) - step)], values[step:])
        done += step
    return values


def _blocks(batch: pa.RecordBatch, hashes: WordHashes, size: int = _BLOCK_WORDS) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(row numbers, starts with the end, word hashes) of runs of rows with about ``size`` words."""
    rows, starts, held, total = [], [0], [], 0
    for i, text in enumerate(byte_texts(batch.column("text"))):
        words = (text or b"").split()
        rows.append(i)
        held.append(hashes.of(words))
        total += len(words)
        starts.append(total)
        if total >= size:
            yield np.array(rows), np.array(starts), np.concatenate(held)
            rows, starts, held, total = [], [0], [], 0
    if rows:
        yield np.array(rows), np.array(starts), np.concatenate(held)


def _whole(starts: np.ndarray, words: np.ndarray) -> np.ndarray:
    """A hash of each document's word sequence, by sums of position-dependent mixes."""
    n = np.diff(starts)
    place = np.arange(len(words)) - np.repeat(starts[:-1], n)
    with np.errstate(over="ignore"):
        parts = mixed(words + mixed(place.astype(np.uint64)))
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(parts, dtype=np.uint64)])
        return mixed(sums[starts[1:]] - sums[starts[:-1]] + mixed(n.astype(np.uint64)))


def _windows(starts: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts of the windows that lie within one document, and the number of its row."""
    lengths = np.diff(starts)
    n = np.maximum(lengths - window + 1, 0)
    owner = np.repeat(np.arange(len(n)), n)
    return np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(starts[:-1], n), owner


def _by_shard(shard: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    order = np.argsort(shard, kind="stable")
    ordered = shard[order]
    cuts = np.flatnonzero(np.append(True, ordered[1:] != ordered[:-1])) if len(order) else []
    for a, b in zip(cuts, np.append(cuts[1:], len(order))):
        yield int(ordered[a]), order[a:b]


def _shard_of(keys: np.ndarray, shards: int) -> np.ndarray:
    return ((keys >> np.uint64(20)) % np.uint64(shards)).astype(np.int64)


def _minimisers(words: np.ndarray, window: int) -> np.ndarray:
    return sliding_least(window_hashes(words, RUN), window - RUN + 1)


def _cuts(values: np.ndarray) -> Iterator[tuple[int, int]]:
    """Bounds of the runs of equal values."""
    if len(values):
        at = np.flatnonzero(np.append(True, values[1:] != values[:-1]))
        yield from zip(at.tolist(), np.append(at[1:], len(values)).tolist())


def _indexed(values: np.ndarray) -> tuple[bytes, bytes]:
    """Distinct values and, for each value, its number among them (16 bits where that suffices)."""
    table, at = np.unique(values, return_inverse=True)
    return table.tobytes(), at.astype(np.uint16 if len(table) < 65_536 else np.uint32).tobytes()


def _values(table: bytes, at: bytes, count: int, kind) -> np.ndarray:
    return np.frombuffer(table, kind)[np.frombuffer(at, np.uint16 if len(at) == 2 * count else np.uint32)]


def _concatenated(parts: list[np.ndarray], kind) -> np.ndarray:
    return np.concatenate(parts) if parts else np.empty(0, kind)


def _distinct_pairs(keys: np.ndarray, docs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (key, doc), sorted."""
    order = np.lexsort((docs, keys))
    keys, docs = keys[order], docs[order]
    fresh = np.append(True, (keys[1:] != keys[:-1]) | (docs[1:] != docs[:-1]))[: len(keys)]
    return keys[fresh], docs[fresh]


def _group_sizes(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(number of its run, size of its run) for each of sorted keys."""
    group = np.cumsum(np.append(True, keys[1:] != keys[:-1])[: len(keys)]) - 1
    return group, np.bincount(group, minlength=1)[group]


def _table(rows: list[tuple], first: str, names: tuple[str, ...]) -> pa.Table:
    """A long column and binary ones from tuples."""
    return pa.table({first: pa.array([x[0] for x in rows], pa.int64())} | {n: pa.array([x[k + 1] for x in rows], pa.binary()) for k, n in enumerate(names)})


_ENTRIES, _KNOWN = ("keys", "counts", "ids", "owners", "wholes", "firsts"), ("docs", "keys", "warm", "copies")


def _told(docs: np.ndarray, keys: np.ndarray, warm: np.ndarray, copies: np.ndarray, buckets: int) -> list[tuple]:
    """Rows of ``_KNOWN`` by bucket."""
    order, there = np.argsort(docs % buckets, kind="stable"), np.argsort(copies % buckets, kind="stable")
    docs, keys, warm, copies = docs[order], keys[order], warm[order], copies[there]
    out = [(int(docs[a] % buckets), docs[a:b].tobytes(), keys[a:b].tobytes(), warm[a:b].tobytes(), b"") for a, b in _cuts(docs % buckets)]
    return out + [(int(copies[a] % buckets), b"", b"", b"", copies[a:b].tobytes()) for a, b in _cuts(copies % buckets)]


def shared_minimisers(docs: DataFrame, window: int, shards: int, buckets: int, hot: int, few: int) -> DataFrame:
    """By bucket of doc_id, packed: (docs, keys, warm) for each minimiser that a document shares
    with another one, and copies, the documents that an earlier one equals word for word."""

    def entries(keys: np.ndarray, docs_: np.ndarray, wholes: np.ndarray, firsts: np.ndarray) -> Iterator[tuple]:
        """By shard: distinct keys, the number of documents of each (0: over ``few``) and these; whole texts and their documents."""
        group, held = _group_sizes(keys)
        head = np.append(True, keys[1:] != keys[:-1])[: len(keys)]
        small = held <= few
        shard = _shard_of(keys[head], shards)
        counts = np.where(small, held, 0)[head].astype(np.uint8)
        by_shard = dict(_by_shard(_shard_of(wholes, shards)))
        entry_of = dict(_by_shard(_shard_of(keys, shards)))
        for s, i in _by_shard(shard):
            mine = entry_of[s]
            w = by_shard.pop(s, np.empty(0, np.int64))
            yield s, keys[head][i].tobytes(), counts[i].tobytes(), *_indexed(docs_[mine[small[mine]]]), wholes[w].tobytes(), firsts[w].tobytes()
        for s, w in by_shard.items():
            yield s, b"", b"", b"", b"", wholes[w].tobytes(), firsts[w].tobytes()

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in batches:
            ids = np.asarray(batch.column("doc_id"))
            for rows, starts, words in _blocks(batch, hashes):
                at, owner = _windows(starts, window)
                if not len(at):
                    continue
                mine = ids[rows]
                keys = _minimisers(words, window)[at]
                first = np.append(True, (keys[1:] != keys[:-1]) | (owner[1:] != owner[:-1]))
                keys, docs_ = _distinct_pairs(keys[first], mine[owner[first]])
                long = np.flatnonzero(np.diff(starts) >= window)
                wholes, firsts = _distinct_pairs(_whole(starts, words)[long], mine[long])
                later = np.append(False, wholes[1:] == wholes[:-1])[: len(wholes)]
                many = _group_sizes(keys)[1] > few
                told = _told(docs_[many], keys[many], np.ones(int(many.sum()), bool), firsts[later], buckets)
                sent = list(entries(keys, docs_, wholes[~later], firsts[~later]))
                none = (None,) * len(_KNOWN)
                # what the block knows itself is passed on by whatever shard
                rows_ = [(*x, None, *none) for x in sent] + [(k % shards, *(None,) * len(_ENTRIES), *x) for k, x in enumerate(told, int(rows[0]))]
                columns = list(zip(*rows_))
                yield pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int64()), *(pa.array(c, pa.binary()) for c in columns[1:7]), pa.array(columns[7], pa.int64()), *(pa.array(c, pa.binary()) for c in columns[8:])], names)
        del hashes
        trim()

    def answer(table: pa.Table) -> pa.Table:
        rows = table.to_pylist()
        told = [(r["bucket"], r["docs"], r["known"], r["warm"], r["copies"]) for r in rows if r["bucket"] is not None]
        rows = [r for r in rows if r["bucket"] is None]
        wholes, firsts = _distinct_pairs(_concatenated([np.frombuffer(r["wholes"], np.uint64) for r in rows], np.uint64), _concatenated([np.frombuffer(r["firsts"], np.int64) for r in rows], np.int64))
        copies = firsts[1:][wholes[1:] == wholes[:-1]]
        keys, docs_, vast = [], [], []
        for r in rows:
            key, count = np.frombuffer(r["keys"], np.uint64), np.frombuffer(r["counts"], np.uint8).astype(np.int64)
            vast.append(key[count == 0])
            keys.append(np.repeat(key, count))
            docs_.append(_values(r["ids"], r["owners"], int(count.sum()), np.int64))
        key, doc = _distinct_pairs(_concatenated(keys, np.uint64), _concatenated(docs_, np.int64))
        held, beyond = _group_sizes(key)[1], np.isin(key, _concatenated(vast, np.uint64))
        keep = (held > 1) | beyond
        return _table(told + _told(doc[keep], key[keep], ((held > hot) | beyond)[keep], copies, buckets), "bucket", _KNOWN)

    names = ["shard", *_ENTRIES, "bucket", "docs", "known", "warm", "copies"]
    sent = docs.mapInArrow(send, ", ".join(f"{n} {'long' if n in ('shard', 'bucket') else 'binary'}" for n in names))
    return sent.repartition(shards, "shard").groupBy("shard").applyInArrow(answer, "bucket long, docs binary, keys binary, warm binary, copies binary")


def _joined(table: pa.Table, column: str, kind) -> np.ndarray:
    return np.frombuffer(b"".join(x or b"" for x in table.column(column).to_pylist()), kind)


def _passages(owner: np.ndarray, at: np.ndarray, keys: np.ndarray, cold: np.ndarray, warm: np.ndarray, rolled: np.ndarray, window: int) -> tuple[np.ndarray, ...]:
    """(start, words, routing key, owner) of runs of cold windows with one minimiser and of single warm windows.

    Runs are cut at ``2 * window`` words (neighbours share ``window - 1``), so that the first
    and the last window of a passage hold all its words between them.
    """
    apart = (keys[1:] != keys[:-1]) | (owner[1:] != owner[:-1])
    begins = cold & np.append(True, ~cold[:-1] | apart)[: len(cold)]
    number = np.arange(len(cold))
    begins |= cold & ((number - np.maximum.accumulate(np.where(begins, number, 0))) % (window + 1) == 0)
    ends = cold & np.append(~cold[1:] | apart | begins[1:], True)[: len(cold)]
    start, single = at[begins], at[warm]
    size = np.concatenate([at[ends] - start + window, np.full(len(single), window)])
    return np.concatenate([start, single]), size, np.concatenate([keys[begins], mixed(rolled[single])]), np.concatenate([owner[begins], owner[warm]])


def _flat(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """All places of the runs that begin at ``starts``."""
    total = int(sizes.sum())
    return np.repeat(starts - (np.cumsum(sizes) - sizes), sizes) + np.arange(total)


def _contents(rolled: np.ndarray, start: np.ndarray, size: np.ndarray, window: int) -> np.ndarray:
    """Names of passages: none is longer than its first and last window together, so these tell all its words."""
    return mixed(rolled[start] ^ mixed(rolled[start + size - window])) + size.astype(np.uint64)


_PACKED = ("words", "coded", "sizes", "which", "docs", "places")


def _packed_rows(words: np.ndarray, rolled: np.ndarray, start: np.ndarray, size: np.ndarray, route: np.ndarray, doc: np.ndarray, place: np.ndarray, window: int, shards: int) -> tuple[list[tuple], tuple[np.ndarray, ...]]:
    """(rows by shard: distinct passages with their places in the smallest document that has them;
    docs, begins and ends of what later documents repeat)."""
    content = _contents(rolled, start, size, window)
    _, first, which = np.unique(content, return_index=True, return_inverse=True)
    least = np.full(len(first), np.iinfo(np.int64).max)
    np.minimum.at(least, which, doc)
    later = doc > least[which]
    out = []
    own = np.flatnonzero(~later)
    for s, i in _by_shard(_shard_of(route[own], shards)):
        i = own[i]
        kinds, at = np.unique(which[i], return_inverse=True)
        head = first[kinds]
        table, coded = _indexed(words[_flat(start[head], size[head])])
        out.append((s, table, coded, size[head].astype(np.uint32).tobytes(), at.astype(np.uint32).tobytes(), doc[i].tobytes(), place[i].astype(np.uint32).tobytes()))
    return out, (doc[later], place[later], place[later] + size[later])


def _marked(docs: np.ndarray, keys: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        return mixed(keys ^ mixed(docs.astype(np.uint64)))


def _spans(doc: np.ndarray, begin: np.ndarray, end: np.ndarray, buckets: int) -> list[tuple]:
    """(bucket, docs, begins, ends), overlapping and adjoining intervals of a document as one."""
    order = np.lexsort((begin, doc, doc % buckets))
    doc, begin, end = doc[order], begin[order], end[order]
    if not len(doc):
        return []
    # ends so far within a document: places are under 2**32, so documents do not mix
    number = np.cumsum(np.append(0, doc[1:] != doc[:-1])) << 32
    reach = np.maximum.accumulate(number + end)
    fresh = np.append(True, number[1:] + begin[1:] > reach[:-1])
    last = np.append(fresh[1:], True)
    doc, begin, end = doc[fresh], begin[fresh], (reach - number)[last]
    return [(int(doc[a] % buckets), doc[a:b].tobytes(), begin[a:b].astype(np.uint32).tobytes(), end[a:b].astype(np.uint32).tobytes()) for a, b in _cuts(doc % buckets)]


def send_passages(docs: DataFrame, known: DataFrame, window: int, shards: int, buckets: int) -> DataFrame:
    """Packed passages by shard, from documents and what ``shared_minimisers`` found, by bucket.

    Rows without words hold intervals (docs, places, sizes: begins and ends) that need no search.
    """

    def run(texts: pa.Table, found: pa.Table) -> pa.Table:
        hashes, out = WordHashes(), []
        entry, is_warm = _marked(_joined(found, "docs", np.int64), _joined(found, "keys", np.uint64)), _joined(found, "warm", bool)
        cold_set, warm_set, copies = np.unique(entry[~is_warm]), np.unique(entry[is_warm]), _joined(found, "copies", np.int64)
        for batch in texts.combine_chunks().to_batches() if len(entry) else ():
            ids = np.asarray(batch.column("doc_id"))
            for rows, starts, words in _blocks(batch, hashes):
                at, owner = _windows(starts, window)
                if len(copies):
                    alive = ~np.isin(ids[rows], copies)[owner]
                    at, owner = at[alive], owner[alive]
                if not len(at):
                    continue
                keys = _minimisers(words, window)[at]
                mark = _marked(ids[rows][owner], keys)
                rolled = window_hashes(words, window)
                start, size, route, own = _passages(owner, at, keys, np.isin(mark, cold_set), np.isin(mark, warm_set), rolled, window)
                packed, later = _packed_rows(words, rolled, start, size, route, ids[rows][own], start - starts[own], window, shards)
                out += packed
                out += [(k % shards, None, None, ends, None, who, begins) for k, (_, who, begins, ends) in enumerate(_spans(*later, buckets), int(rows[0]))]
        del hashes
        trim()
        return _table(out, "shard", _PACKED)

    return docs.groupBy("bucket").cogroup(known.groupBy("bucket")).applyInArrow(run, "shard long, " + ", ".join(f"{x} binary" for x in _PACKED))


def repeated_windows(blocks: list[tuple[bytes, ...]], window: int) -> tuple[np.ndarray, np.ndarray]:
    """(doc, window start) of all windows that an earlier document also has, by an index of the passages."""
    flats, sizes, which, docs, places, base = [], [], [], [], [], 0
    for table, coded, size, at, doc, place in blocks:
        size = np.frombuffer(size, np.uint32).astype(np.int64)
        flats.append(_values(table, coded, int(size.sum()), np.uint64))
        sizes.append(size)
        which.append(np.frombuffer(at, np.uint32).astype(np.int64) + base)
        docs.append(np.frombuffer(doc, np.int64))
        places.append(np.frombuffer(place, np.uint32).astype(np.int64))
        base += len(size)
    if not base:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    flat, size, at, doc, place = (np.concatenate(x) for x in (flats, sizes, which, docs, places))
    # equal passages of different blocks become one
    start = np.cumsum(size) - size
    _, first, same = np.unique(_contents(window_hashes(flat, window), start, size, window), return_index=True, return_inverse=True)
    at = same[at]
    start, size = start[first], size[first]
    known, rank = np.unique(doc, return_inverse=True)
    least = np.full(len(size), len(known), np.int32)
    np.minimum.at(least, at, rank.astype(np.int32))
    _, symbols = np.unique(flat[_flat(start, size)], return_inverse=True)
    # the text of the index: passages with a separator after each
    begin = np.cumsum(size + 1) - (size + 1)
    text = np.zeros(int((size + 1).sum()), np.int32)
    text[_flat(begin, size)] = symbols + 1
    del flat, flats, symbols
    index = FmIndex(text, np.repeat(least, size + 1), window)
    # all passages are streamed: the matching statistic and the smallest document at every position
    windows = size - window + 1
    ends = _flat(begin, windows)
    earliest = np.empty(len(ends), np.int32)
    for k in range(0, len(ends), 1 << 17):
        matched, lowest = index.matching_statistics(text, ends[k : k + (1 << 17)] + window, window)
        earliest[k : k + (1 << 17)] = np.where(matched >= window, lowest, len(known))
    lane_of = np.cumsum(windows) - windows
    n = windows[at]
    who, where = np.repeat(rank, n), _flat(place, n)
    hit = earliest[_flat(lane_of[at], n)] < who
    return known[who[hit]], where[hit]


def search_shards(passages: DataFrame, window: int, shards: int, buckets: int) -> DataFrame:
    """By bucket of doc_id, packed: docs with the (begin, end) word intervals to remove."""

    def run(table: pa.Table) -> pa.Table:
        rows = list(zip(*(table.column(x).to_pylist() for x in _PACKED)))
        given = [r for r in rows if r[0] is None]
        doc, at = repeated_windows([r for r in rows if r[0] is not None], window)
        doc = np.concatenate([doc, *(np.frombuffer(r[4], np.int64) for r in given)])
        begin = np.concatenate([at, *(np.frombuffer(r[5], np.uint32).astype(np.int64) for r in given)])
        end = np.concatenate([at + window, *(np.frombuffer(r[2], np.uint32).astype(np.int64) for r in given)])
        trim()
        return _table(_spans(doc, begin, end, buckets), "bucket", ("docs", "begins", "ends"))

    return passages.repartition(shards, "shard").groupBy("shard").applyInArrow(run, "bucket long, docs binary, begins binary, ends binary")


def _prime_from(n: int) -> int:
    while any(n % k == 0 for k in range(2, int(n**0.5) + 1)):
        n += 1
    return n


def repeated_spans(docs: DataFrame, window: int = WINDOW, hot: int = HOT) -> tuple[DataFrame, int]:
    """By bucket (doc_id modulo the number returned): docs with packed intervals; no ends: the whole text."""
    if window < RUN:
        raise ValueError(f"a window has at least {RUN} words")
    docs = docs.where("doc_id IS NOT NULL AND text IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    shards = max(1, -(-size // SHARD_BYTES))
    buckets = _prime_from(shards + 1)
    known = materialise(shared_minimisers(docs, window, shards, buckets, hot, FEW), "minimisers")
    placed = docs.withColumn("bucket", F.pmod("doc_id", F.lit(buckets)))
    spans = materialise(search_shards(send_passages(placed, known, window, shards, buckets), window, shards, buckets), "spans")
    none = F.lit(None).cast("binary")
    copies = known.where(F.octet_length("copies") > 0).select("bucket", F.col("copies").alias("docs"), none.alias("begins"), none.alias("ends"))
    return spans.unionByName(copies), buckets


def covered(begins: np.ndarray, ends: np.ndarray, words: int) -> np.ndarray:
    steps = np.bincount(np.minimum(begins, words), minlength=words + 1) - np.bincount(np.minimum(ends, words), minlength=words + 1)
    return np.cumsum(steps)[:-1] > 0


def remove_repeats(docs: DataFrame, window: int = WINDOW, with_text: bool = False, hot: int = HOT) -> DataFrame:
    """``docs`` with n_words, n_removed and kept_sha256; ``with_text`` replaces text (kept words,
    one space between) where words were removed."""
    names = ["n_words", "n_removed", "kept_sha256"]
    docs = docs.drop(*names, "__bucket")
    spans, buckets = repeated_spans(docs, window, hot)
    columns = docs.columns

    def cut(texts: pa.Table, found: pa.Table | None) -> pa.Table:
        owner, begin, end = [], [], []
        for row in found.to_pylist() if found is not None else ():
            ids = np.frombuffer(row["docs"], np.int64)
            owner.append(ids)
            begin.append(np.zeros(len(ids), np.int64) if row["ends"] is None else np.frombuffer(row["begins"], np.uint32).astype(np.int64))
            end.append(np.full(len(ids), 1 << 40) if row["ends"] is None else np.frombuffer(row["ends"], np.uint32).astype(np.int64))
        owner, begin, end = (np.concatenate(x) if x else np.empty(0, np.int64) for x in (owner, begin, end))
        order = np.argsort(owner, kind="stable")
        owner, begin, end = owner[order], begin[order], end[order]
        out: list[list] = [[] for _ in range(4)]
        for doc_id, text in zip(texts.column("doc_id").to_pylist(), byte_texts(texts.column("text").combine_chunks())):
            words = (text or b"").split()
            kept = words
            if doc_id is not None and len(owner):
                a, b = np.searchsorted(owner, [doc_id, doc_id + 1])
                if b > a:
                    kept = [words[i] for i in np.flatnonzero(~covered(begin[a:b], end[a:b], len(words))).tolist()]
            line = b" ".join(kept)
            for column, value in zip(out, (len(words), len(words) - len(kept), hashlib.sha256(line).hexdigest(), line.decode("utf-8") if len(kept) < len(words) else None)):
                column.append(value)
        made = {c: texts.column(c) for c in columns}
        if with_text:
            made["text"] = pa.array([t if o is None else o for t, o in zip(texts.column("text").to_pylist(), out[3])], pa.string())
        return pa.table(made | {n: pa.array(x, t) for n, x, t in zip(names, out, (pa.int64(), pa.int64(), pa.string()))})

    def alone(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield from cut(pa.Table.from_batches([batch]), None).to_batches()

    schema = ", ".join([*(f"`{f.name.replace('`', '``')}` {f.dataType.simpleString()}" for f in docs.schema.fields), "n_words long, n_removed long, kept_sha256 string"])
    placed = docs.where("doc_id IS NOT NULL").withColumn("__bucket", F.pmod(F.col("doc_id").cast("long"), F.lit(buckets)))
    done = placed.groupBy("__bucket").cogroup(spans.groupBy("bucket")).applyInArrow(cut, schema)
    # rows without an id take no part, and may be many: they are cut where they are
    return done.unionByName(docs.where("doc_id IS NULL").mapInArrow(alone, schema))
