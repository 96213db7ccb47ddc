"""Ids of whole texts by the public tokenizers library, each distinct piece once.

A byte-level pre-tokeniser always ends a unit before a space that a non-space follows,
so a text may be cut there and each distinct piece encoded once.  ``PieceEncoder``
gives the same ids as encoding the whole text; ``tests/llm`` holds both side by side.
"""

from __future__ import annotations

import os
import re
from array import array

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import per_worker

#: A space that may not be a cut: white space or the end follows.
_UNSAFE = r" ([\s\p{Z}\x{85}\x{1c}-\x{1f}]|\z)"
_CUT = re.compile(r" (?=\S)")


class PieceEncoder:
    """Encode string arrays to little-endian unsigned 32-bit ids, each distinct piece once.

    Pieces without white space are encoded many at a time, joined by spaces (or, at the
    start of a line, by line ends); in such a text only the first token of a piece holds
    the byte of a space, so the ids fall apart again where those tokens stand.  Nothing
    is kept from one array to the next, so memory follows the array alone.
    """

    def __init__(self, vocabulary: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(vocabulary)
        words = self.tokenizer.get_vocab()
        self.opens = np.zeros(max(words.values()) + 1, bool)
        self.opens[[i for w, i in words.items() if w.startswith("\u0120")]] = True
        self.line_end = words["\u010a"]
        specials = [re.escape(x.content) for x in self.tokenizer.get_added_tokens_decoder().values()]
        self.rough = "|".join([r"^\z", r"[\s\p{Z}\x{85}\x{1c}-\x{1f}]", *specials])

    def _each(self, texts: list[str]) -> list[bytes]:
        got = self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)
        return [array("I", x.ids).tobytes() for x in got]

    def _joined(self, pieces: pa.Array, mark: str, group: int = 500) -> pa.Array:
        """Ids of ``mark`` + piece (a space) or of the piece alone (a line end), for plain pieces."""
        words, found, starts, base = pieces.to_pylist(), [], [], 0
        for at in range(0, len(words), group):
            part = words[at : at + group]
            ids = np.array(self.tokenizer.encode_batch_fast([mark + mark.join(part)], add_special_tokens=False)[0].ids, np.uint32)
            first = np.flatnonzero(self.opens[ids] if mark == " " else ids == self.line_end)
            if len(first) != len(part):
                raise ValueError("the vocabulary's pre-tokeniser does not end a piece before a space")
            if mark != " ":
                ids, first = np.delete(ids, first), first - np.arange(len(first))
            found.append(ids)
            starts.append(first + base)
            base += len(ids)
        bounds = np.append(np.concatenate(starts) if starts else np.empty(0, np.int64), base).astype(np.int64) * 4
        ids = np.concatenate(found) if found else np.empty(0, np.uint32)
        return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(pieces), [None, pa.py_buffer(bounds), pa.py_buffer(ids)])

    def _distinct(self, pieces: pa.Array, mark: str) -> pa.Array:
        """Ids of these pieces; a last stop or comma is encoded apart, odd pieces one by one."""
        rough = np.asarray(pc.match_substring_regex(pieces, self.rough))
        odd = pieces.filter(pa.array(rough)).to_pylist()
        lines: dict[int, tuple[str, str]] = {}
        if mark == " ":  # "end.\nStart" is two pieces with a line end between them
            hard = np.asarray(pc.match_substring_regex(pc.replace_substring(pa.array(odd, pa.large_string()), "\n", "", max_replacements=1), self.rough))
            for i, x in enumerate(odd):
                a, end, b = x.partition("\n")
                if end and a and b and not hard[i]:
                    lines[i] = (a, b)
        plain = pieces.filter(pa.array(~rough))
        closed = pc.match_substring_regex(plain, r"\p{L}[.,]\z")
        trimmed = pc.utf8_slice_codeunits(plain.filter(closed), 0, -1)
        coded = pa.concat_arrays([plain.filter(pc.invert(closed)), trimmed, pa.array([a for a, _ in lines.values()], pa.large_string())]).dictionary_encode()
        ids = self._joined(coded.dictionary, mark).take(coded.indices.cast(pa.int64()))
        n, m = len(plain) - len(trimmed), len(trimmed)
        last = pc.utf8_slice_codeunits(plain.filter(closed), -1)
        ends = pa.array(self._each([".", ","]), pa.large_binary()).take(pc.index_in(last, pa.array([".", ","], pa.large_string())))
        values = [ids.slice(0, n), pc.binary_join_element_wise(ids.slice(n, m), ends, pa.scalar(b"", pa.large_binary()))]
        alone = [i for i in range(len(odd)) if i not in lines]
        others: list[bytes] = [b""] * len(odd)
        for i, got in zip(alone, self._each([mark.strip("\n") + odd[i] for i in alone])):
            others[i] = got
        if lines:
            starts = self._distinct(pa.array([b for _, b in lines.values()], pa.large_string()), "\n").to_pylist()
            middle = array("I", [self.line_end]).tobytes()
            for i, head, tail in zip(lines, ids.slice(n + m).to_pylist(), starts):
                others[i] = head + middle + tail
        order, is_closed = np.flatnonzero(~rough), np.asarray(closed)
        place = np.empty(len(pieces), np.int64)
        place[np.concatenate([order[~is_closed], order[is_closed], np.flatnonzero(rough)])] = np.arange(len(pieces))
        return pa.concat_arrays([*values, pa.array(others, pa.large_binary())]).take(pa.array(place))

    def encode(self, texts: pa.Array) -> list[bytes]:
        """One byte string of ids for each text of a string array; a null text counts as empty."""
        texts = pc.fill_null(texts.cast(pa.large_string()), "")
        unsafe = np.asarray(pc.match_substring_regex(texts, _UNSAFE))
        out: list[bytes] = [b""] * len(texts)
        for i in np.flatnonzero(unsafe).tolist():
            head, *tail = _CUT.split(texts[i].as_py())
            coded = pa.array(tail, pa.large_string()).dictionary_encode()
            tail = self._distinct(coded.dictionary, " ").take(coded.indices.cast(pa.int64()))
            out[i] = self._each([head])[0] + b"".join(tail.to_pylist())
        safe = np.flatnonzero(~unsafe)
        if not len(safe):
            return out
        cut = pc.split_pattern(texts.take(pa.array(safe)) if len(safe) < len(texts) else texts, " ")
        bounds, parts = np.asarray(cut.offsets), cut.values
        heads = self._distinct(parts.take(pa.array(bounds[:-1])), "\n")
        coded = parts.dictionary_encode()
        codes = np.array(coded.indices, np.int64)
        codes[bounds[:-1]] = len(coded.dictionary) + np.arange(len(heads))
        ids = pa.concat_arrays([self._distinct(coded.dictionary, " "), heads]).take(pa.array(codes))
        at = np.frombuffer(ids.buffers()[1], np.int64)[bounds].tolist()
        raw = memoryview(ids.buffers()[2] or b"")
        for i, start, end in zip(safe.tolist(), at[:-1], at[1:]):
            out[i] = bytes(raw[start:end])
        return out


def encoder(vocabulary: str) -> PieceEncoder:
    return per_worker(("pieces", vocabulary), lambda: PieceEncoder(vocabulary))


def in_chunks(texts: pa.Array, weight: int = 24_000_000):
    """(start, slice) of a text column, each slice of about ``weight`` bytes, in order."""
    ends = np.cumsum(np.asarray(pc.fill_null(pc.binary_length(texts), 0), np.int64))
    start = 0
    while start < len(texts):
        before = ends[start - 1] if start else 0
        end = max(start + 1, int(np.searchsorted(ends, before + weight, "right")))
        yield start, texts.slice(start, end - start)
        start = end
