"""SentencePiece encoding and decoding with forward states shared by common prefixes.

The distinct marked words of a batch are sorted, which is the depth-first order of
their trie; going from one word to the next keeps the forward states of their common
prefix and extends only what differs.  A state is the best score of a segmentation of
the prefix and its last piece (Viterbi); of equal scores the longest last piece counts,
as in the library.  The scores are those of the model file's pieces, read as a unigram
model whatever trainer made them (``kind="unigram"``, the registered query).

With ``kind="bpe"`` a state is the last piece of the prefix's own encoding by merges: a
piece may follow it only if merging the two texts gives these two pieces back, and
adjacent pairs that all hold make the encoding of the whole.  Both kinds give the ids of
the public library with a model of that kind, which ``tests/llm`` checks.

A null or empty text has no ids, characters outside the vocabulary become byte pieces
(or the unknown id), texts that hold the mark U+2581 itself decode to spaces, as in
the library.
"""

from __future__ import annotations

import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import per_worker
from .tokens import in_chunks

MARK = "▁"
_WORD = re.compile(f"{MARK}*[^{MARK}]+|{MARK}+")
_MAX_PAIRS = 1_000_000
_MAX_WORDS = 300_000


class SharedPrefixEncoder:
    """Encode marked words.  ``kind`` is "unigram" or "bpe"; ``byte_ids`` has an id per byte or is empty."""

    def __init__(self, pieces: dict[str, int], scores: dict[int, float], kind: str, unknown: int, byte_ids: list[int]):
        self.ids, self.scores, self.kind, self.unknown, self.byte_ids = pieces, scores, kind, unknown, byte_ids
        self.longest = max(map(len, pieces), default=1)
        self.texts = {i: x for x, i in pieces.items()}
        self.joins = {x[k : k + 2] for x in pieces for k in range(len(x) - 1)}
        #: by the last three characters (all, if fewer): the lengths of the pieces that end so, longest first
        ends: dict[str, set[int]] = {}
        for x in pieces:
            ends.setdefault(x[-3:], set()).add(len(x))
        self.lengths = {x: tuple(sorted(found, reverse=True)) for x, found in ends.items()}
        self.floor = min(scores.values(), default=0.0) - 10.0
        self.pairs: dict[tuple[int, int], bool] = {}
        self.whole: dict[int, bool] = {}

    def merged(self, text: str) -> list[str]:
        """Byte-pair merging by the score of the merged piece, leftmost first."""
        parts = list(text)
        while True:
            best, at = None, -1
            for k in range(len(parts) - 1):
                i = self.ids.get(parts[k] + parts[k + 1])
                if i is not None and (best is None or self.scores[i] > best):
                    best, at = self.scores[i], k
            if at < 0:
                return parts
            parts[at : at + 2] = [parts[at] + parts[at + 1]]

    def _stands(self, i: int) -> bool:
        if i not in self.whole:
            self.whole[i] = self.merged(self.texts[i]) == [self.texts[i]]
        return self.whole[i]

    def _follows(self, a: int, b: int) -> bool:
        key = (a, b)
        if (held := self.pairs.get(key)) is None:
            if len(self.pairs) > _MAX_PAIRS:
                self.pairs.clear()
            x, y = self.texts[a], self.texts[b]
            held = self.pairs[key] = self.merged(x + y) == [x, y]
        return held

    def _spell(self, char: str) -> list[int]:
        return [self.byte_ids[b] for b in char.encode()] if self.byte_ids else [self.unknown]

    def encode_sorted(self, words: list[str]) -> list[list[int]]:
        """Ids of each word; the words must be in sorted order."""
        step = self._extend_pairs if self.kind == "bpe" else self._extend_scores
        out: list[list[int]] = []
        #: states[i]: (start of the last piece, its id or -1, start of its segment, score) of the prefix of i characters
        states: list[tuple[int, int, int, float]] = [(0, -2, 0, 0.0)]
        before = ""
        for word in words:
            shared = 0
            for a, b in zip(before, word):
                if a != b:
                    break
                shared += 1
            del states[shared + 1 :]
            step(word, shared, states)
            before = word
            ids: list[int] = []
            end = len(word)
            while end:
                start, piece, _, _ = states[end]
                ids.extend([piece] if piece >= 0 else reversed(self._spell(word[start:end])))
                end = start
            ids.reverse()
            out.append(ids)
        return out

    def _extend_pairs(self, word: str, done: int, states: list) -> None:
        ids, joins, lengths, pairs, whole = self.ids, self.joins, self.lengths.get, self.pairs.get, self.whole.get
        for end in range(done + 1, len(word) + 1):
            floor = states[end - 1][2] if end > 1 and word[end - 2 : end] in joins else end - 1
            found = -1
            for width in (3, 2, 1):  # pieces of three and more characters, of two, of one
                for n in lengths(word[end - width : end], ()) if end - width >= floor else ():
                    start = end - n
                    if start < floor:
                        continue
                    piece = ids.get(word[start:end])
                    if piece is None:
                        continue
                    last = states[start][1]
                    if start == floor or last < 0:
                        fits = whole(piece)
                        if fits is None:
                            fits = self._stands(piece)
                    else:
                        fits = pairs((last, piece))
                        if fits is None:
                            fits = self._follows(last, piece)
                    if fits:
                        found = start
                        break
                if found >= 0:
                    break
            # a character that no piece has never merges, so what follows starts anew
            states.append((found, piece, floor, 0.0) if found >= 0 else (end - 1, -1, floor, 0.0))

    def _extend_scores(self, word: str, done: int, states: list) -> None:
        known, scores, lengths = self.ids.get, self.scores, self.lengths.get
        for end in range(done + 1, len(word) + 1):
            # a character that no piece has costs more than the worst piece
            start, piece, best = end - 1, -1, states[end - 1][3] + self.floor
            for width in (3, 2, 1):  # pieces of three and more characters, of two, of one: longest first
                for n in lengths(word[end - width : end], ()) if end >= width else ():
                    if n > end:
                        continue
                    at = known(word[end - n : end])
                    if at is None:
                        continue
                    score = states[end - n][3] + scores[at]
                    if score > best:
                        start, piece, best = end - n, at, score
            states.append((start, piece, 0, best))


class PieceCodec:
    """Texts to ids and back by a SentencePiece model file; ``kind`` overrides the file's own."""

    def __init__(self, model: str, kind: str | None = None):
        import sentencepiece
        from sentencepiece import sentencepiece_model_pb2

        self.library = sentencepiece.SentencePieceProcessor(model_file=model)
        with open(model, "rb") as f:
            spec = sentencepiece_model_pb2.ModelProto.FromString(f.read())
        rule = spec.normalizer_spec
        self.plain = rule.name == "identity" and not rule.remove_extra_whitespaces and rule.add_dummy_prefix
        n = self.library.get_piece_size()
        kept = [i for i in range(n) if not (self.library.is_control(i) or self.library.is_unknown(i) or self.library.is_byte(i) or self.library.is_unused(i))]
        pieces = {self.library.id_to_piece(i): i for i in kept}
        coded = {self.library.id_to_piece(i): i for i in range(n) if self.library.is_byte(i)}
        byte_ids = [coded[f"<0x{b:02X}>"] for b in range(256)] if len(coded) == 256 else []
        self.words = SharedPrefixEncoder(pieces, {i: self.library.get_score(i) for i in kept}, kind or ("bpe" if spec.trainer_spec.model_type == 2 else "unigram"), self.library.unk_id(), byte_ids)
        if any(MARK in x.lstrip(MARK) for x in pieces):
            raise ValueError("pieces reach over the start of a word")
        self.memo: list[dict[str, bytes]] = [{}, {}]
        self.breaks = not any("\n" in x for x in pieces)
        self.raw = [b""] * n
        for x, i in pieces.items():
            self.raw[i] = x.encode()
        for b, i in enumerate(byte_ids):
            self.raw[i] = bytes([b])
        self.raw[self.library.unk_id()] = " ⁇ ".encode()

    def _distinct(self, words: list[str]) -> list[bytes]:
        """Ids of distinct marked words; at line ends, which no piece holds, they are cut."""
        split = {x: x.split("\n") for x in words if self.breaks and "\n" in x}
        todo = {x for x in words if x not in split}
        for parts in split.values():
            todo.update(parts)
        todo.discard("")
        new, old = self.memo
        if len(new) > _MAX_WORDS:
            new, old = self.memo = [{}, new]
        ids = {x: y for x in todo if (y := new.get(x) or old.get(x)) is not None}
        order = sorted(todo - ids.keys())
        ids.update(zip(order, [array("I", x).tobytes() for x in self.words.encode_sorted(order)]))
        new |= ids
        ids[""] = b""
        end = np.array(self.words._spell("\n"), np.uint32).tobytes()
        for x, parts in split.items():
            ids[x] = end.join(ids[p] for p in parts)
        return [ids[x] for x in words]

    def encode(self, texts: pa.Array) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text."""
        texts = pc.fill_null(texts.cast(pa.large_string()), "")
        odd = np.asarray(pc.match_substring_regex(texts, f"^\\z|  | \\z|^ |{MARK}")) if self.plain else np.ones(len(texts), bool)
        out: list[bytes] = [b""] * len(texts)
        rest = {i: _WORD.findall(self.normalised(texts[i].as_py())) for i in np.flatnonzero(odd).tolist()}
        distinct = list({w for ws in rest.values() for w in ws})
        known = dict(zip(distinct, self._distinct(distinct)))
        for i, ws in rest.items():
            out[i] = b"".join([known[w] for w in ws])
        plain = np.flatnonzero(~odd)
        if not len(plain):
            return out
        cut = pc.split_pattern(texts.take(pa.array(plain)) if len(plain) < len(texts) else texts, " ")
        coded = cut.values.dictionary_encode()
        ids = pa.array(self._distinct([MARK + x for x in coded.dictionary.to_pylist()]), pa.large_binary()).take(coded.indices.cast(pa.int64()))
        at = np.frombuffer(ids.buffers()[1], np.int64)[np.asarray(cut.offsets)].tolist()
        raw = memoryview(ids.buffers()[2] or b"")
        for i, start, end in zip(plain.tolist(), at[:-1], at[1:]):
            out[i] = bytes(raw[start:end])
        return out

    def normalised(self, text: str) -> str:
        if not self.plain:
            return self.library.normalize(text)
        return MARK + text.replace(" ", MARK) if text else ""

    def decode(self, ids: bytes) -> str:
        """The text of these ids; the mark that stands before the first word is dropped."""
        raw = self.raw
        text = b"".join([raw[i] for i in np.frombuffer(ids, np.uint32).tolist()]).decode("utf-8", "replace")
        return text.replace(MARK, " ").removeprefix(" ")


def encode_pieces(docs: DataFrame, model: str, with_ids: bool = False, kind: str | None = None) -> DataFrame:
    """doc_id, n_pieces, ids_crc32, decoded_crc32 (of the decoded UTF-8), round_trip, and the ids if wanted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = per_worker(("pieces", model, kind), lambda: PieceCodec(model, kind))
        for batch in batches:
            for start, texts in in_chunks(batch.column("text")):
                ids = codec.encode(texts)
                back = [codec.decode(x) for x in ids]
                columns = {
                    "doc_id": batch.column("doc_id").slice(start, len(texts)),
                    "n_pieces": pa.array([len(x) // 4 for x in ids], pa.int64()),
                    "ids_crc32": pa.array([zlib.crc32(x) for x in ids], pa.int64()),
                    "decoded_crc32": pa.array([zlib.crc32(x.encode()) for x in back], pa.int64()),
                    "round_trip": pa.array([x == (y or "") for x, y in zip(back, texts.to_pylist())], pa.bool_()),
                }
                if with_ids:
                    columns["ids"] = pa.array([np.frombuffer(x, np.uint32).tolist() for x in ids], pa.list_(pa.int64()))
                yield pa.RecordBatch.from_pydict(columns)

    schema = "doc_id long, n_pieces long, ids_crc32 long, decoded_crc32 long, round_trip boolean"
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, schema + (", ids array<long>" if with_ids else ""))


def decode_pieces(encoded: DataFrame, model: str) -> DataFrame:
    """doc_id and text from rows with ``ids`` (a null list decodes to the empty text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = per_worker(("pieces", model), lambda: PieceCodec(model))
        for batch in batches:
            texts = [codec.decode(np.array(x or [], np.uint32).tobytes()) for x in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column("doc_id"), "text": pa.array(texts, pa.string())})

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")
