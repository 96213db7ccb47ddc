"""Language identification by a bidirectional gated recurrent network over bytes.

The network reads the bytes of one word (with its end marks) in both directions, labels
every position with language probabilities, and a document's probabilities are the mean
over all positions of its words that hold a letter.  Since its state starts anew at
each word, a word that occurs again has the same labels, so each distinct word of a
batch is read once and counted as often as it stands there; whole texts are covered,
never a prefix.  Words over ``MAX_BYTES`` bytes are read in parts of at most that length
that end between characters.

It is trained in numpy by backpropagation through time on the distinct words (all of
their parts) of a bounded sample of labelled documents, each with the shares of the
languages it was seen in.  The README states what the restart at each word saves.

Null texts and texts without any letter get ``und`` and score 0.  With no labelled
document every text is ``und``.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_sample, byte_texts, id_bucket, materialise, with_columns

MAX_BYTES = 24
#: Symbols: the 256 bytes, the mark before and after each word.
EDGE, SYMBOLS = 256, 257


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (np.tanh(0.5 * x) + 1.0)


class ByteGru:
    """Two gated recurrent layers, one per direction, and a softmax at every position."""

    def __init__(self, languages: list[str], hidden: int = 12, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.languages, self.hidden = languages, hidden
        self.weights: dict[str, np.ndarray] = {}
        for d in "fb":
            self.weights[f"x{d}"] = rng.normal(0, 0.3, (SYMBOLS, 3 * hidden)).astype(np.float32)
            self.weights[f"h{d}"] = rng.normal(0, 1 / np.sqrt(hidden), (hidden, 3 * hidden)).astype(np.float32)
            self.weights[f"o{d}"] = rng.normal(0, 0.3, (hidden, len(languages))).astype(np.float32)
        self.weights["bias"] = np.zeros(len(languages), np.float32)

    def _pass(self, x: np.ndarray, direction: str, keep: bool = False):
        """Hidden states (time, lanes, hidden) of symbols (time, lanes); z, r, candidate and r*h if kept."""
        steps, lanes = x.shape
        n, w, u = self.hidden, self.weights[f"x{direction}"], self.weights[f"h{direction}"]
        h = np.zeros((lanes, n), np.float32)
        states = np.empty((steps, lanes, n), np.float32)
        trace = []
        for t in range(steps):
            gates = w[x[t]]
            zr = _sigmoid(gates[:, : 2 * n] + h @ u[:, : 2 * n])
            z, r = zr[:, :n], zr[:, n:]
            reset = r * h
            c = np.tanh(gates[:, 2 * n :] + reset @ u[:, 2 * n :])
            if keep:
                trace.append((h, z, r, c, reset))
            h = h + z * (c - h)
            states[t] = h
        return states, trace

    def positions(self, x: np.ndarray) -> np.ndarray:
        """Probabilities (time, lanes, languages) for words of equal length."""
        w = self.weights
        logits = self._pass(x, "f")[0] @ w["of"] + self._pass(x[::-1], "b")[0][::-1] @ w["ob"] + w["bias"]
        e = np.exp(logits - logits.max(-1, keepdims=True))
        return e / e.sum(-1, keepdims=True)

    def gradients(self, x: np.ndarray, target: np.ndarray, weight: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Mean weighted cross entropy over positions and its gradients, through time."""
        w, n = self.weights, self.hidden
        sides = {"f": (x, *self._pass(x, "f", True)), "b": (x[::-1], *self._pass(x[::-1], "b", True))}
        hf, hb = sides["f"][1], sides["b"][1][::-1]
        logits = hf @ w["of"] + hb @ w["ob"] + w["bias"]
        logits -= logits.max(-1, keepdims=True)
        p = np.exp(logits)
        p /= p.sum(-1, keepdims=True)
        scale = weight / (weight.sum() * len(x))
        loss = float(-(np.log(p + 1e-9) * target * scale[:, None]).sum())
        d = (p - target) * scale[:, None]
        out = {"of": np.einsum("tlh,tlc->hc", hf, d), "ob": np.einsum("tlh,tlc->hc", hb, d), "bias": d.sum((0, 1))}
        for side, (symbols, _, trace) in sides.items():
            u = w[f"h{side}"]
            above = d @ w[f"o{side}"].T
            above = above if side == "f" else above[::-1]
            gx, gu = np.zeros_like(w[f"x{side}"]), np.zeros_like(u)
            back = np.zeros_like(above[0])
            for t in reversed(range(len(symbols))):
                h, z, r, c, reset = trace[t]
                dh = above[t] + back
                dc = dh * z * (1 - c * c)
                dz = dh * (c - h) * z * (1 - z)
                dreset = dc @ u[:, 2 * n :].T
                dr = dreset * h * r * (1 - r)
                gates = np.concatenate([dz, dr, dc], 1)
                np.add.at(gx, symbols[t], gates)
                gu[:, : 2 * n] += h.T @ gates[:, : 2 * n]
                gu[:, 2 * n :] += reset.T @ dc
                back = dh * (1 - z) + dreset * r + gates[:, : 2 * n] @ u[:, : 2 * n].T
            out[f"x{side}"], out[f"h{side}"] = gx, gu
        return loss, out

    def fit(self, batches: list[tuple[np.ndarray, np.ndarray, np.ndarray]], epochs: int, rate: float = 0.01, seed: int = 3) -> list[float]:
        """Adam over the batches; the mean loss of each epoch."""
        rng, losses, step = np.random.default_rng(seed), [], 0
        first = {k: np.zeros_like(v) for k, v in self.weights.items()}
        second = {k: np.zeros_like(v) for k, v in self.weights.items()}
        for epoch in range(epochs):
            seen = []
            for i in rng.permutation(len(batches)):
                loss, g = self.gradients(*batches[i])
                seen.append(loss)
                step += 1
                now = rate * (1 - epoch / epochs) * np.sqrt(1 - 0.999**step) / (1 - 0.9**step)
                for k, v in g.items():
                    first[k] = 0.9 * first[k] + 0.1 * v
                    second[k] = 0.999 * second[k] + 0.001 * v * v
                    self.weights[k] = self.weights[k] - (now * first[k] / (np.sqrt(second[k]) + 1e-8)).astype(np.float32)
            losses.append(float(np.mean(seen)))
        return losses


def _lanes(words: list[bytes]) -> np.ndarray:
    """(time, lanes) symbols of words of one length, with their end marks."""
    raw = np.frombuffer(b"".join(words), np.uint8).reshape(len(words), -1).T
    edge = np.full((1, len(words)), EDGE, np.int64)
    return np.concatenate([edge, raw.astype(np.int64), edge])


def _pieces(word: bytes) -> list[bytes]:
    """Parts of at most MAX_BYTES bytes; a part ends between characters where the bytes are UTF-8."""
    if len(word) <= MAX_BYTES:
        return [word]
    out, at = [], 0
    while at < len(word):
        end = min(at + MAX_BYTES, len(word))
        cut = end
        while cut < len(word) and cut > end - 4 and word[cut] & 0xC0 == 0x80:
            cut -= 1
        end = cut if cut > at and (cut == len(word) or word[cut] & 0xC0 != 0x80) else end
        out.append(word[at:end])
        at = end
    return out


def word_parts(words: list[bytes]) -> tuple[list[bytes], list[int]]:
    """Words cut into parts, and the word that each part comes from."""
    parts, owner = [], []
    for i, x in enumerate(words):
        for part in _pieces(x):
            parts.append(part)
            owner.append(i)
    return parts, owner


def word_sums(model: ByteGru, words: list[bytes], lanes: int = 8192) -> np.ndarray:
    """For each word the sum of its positions' probabilities and, last, the number of positions."""
    parts, owner = word_parts(words)
    out = np.zeros((len(words), len(model.languages) + 1), np.float64)
    sizes = np.array([len(x) for x in parts], np.int64)
    for n in np.unique(sizes).tolist():
        which = np.flatnonzero(sizes == n)
        for at in range(0, len(which), lanes):
            part = which[at : at + lanes]
            p = model.positions(_lanes([parts[i] for i in part.tolist()]))[1:-1].sum(0)
            np.add.at(out, np.array(owner)[part], np.concatenate([p, np.full((len(part), 1), n)], 1))
    return out


def label_positions(model: ByteGru, text: str) -> list[tuple[int, str, float]]:
    """(byte offset, language, probability) of every byte that is no white space."""
    raw, out, at = text.encode(), [], 0
    for word in raw.split():
        at = raw.index(word, at)
        for part in _pieces(word):
            p = model.positions(_lanes([part]))[1:-1, 0]
            out += [(at + j, model.languages[int(q.argmax())], float(q.max())) for j, q in enumerate(p)]
            at += len(part)
    return out


class DocumentLabeller:
    """Pools word sums to documents; a memo of word rows is bounded by ``limit`` words."""

    def __init__(self, model: ByteGru, limit: int = 150_000):
        self.model, self.limit = model, limit
        self.known: dict[bytes, int] = {}
        self.rows = np.zeros((0, len(model.languages) + 1))

    def _learn(self, words: set[bytes]) -> None:
        new = [x for x in words if x not in self.known]
        if len(self.known) + len(new) > self.limit:
            self.known, self.rows, new = {}, self.rows[:0], list(words)
        sums = word_sums(self.model, new)
        for i, x in enumerate(new):
            if not any(map(str.isalpha, x.decode("utf-8", "replace"))):
                sums[i] = 0.0
        self.known.update(zip(new, range(len(self.rows), len(self.rows) + len(new))))
        self.rows = np.concatenate([self.rows, sums])

    def label(self, texts: list[bytes | None]) -> list[tuple[str, float, np.ndarray]]:
        """(language or und, its pooled probability, all probabilities) for each text."""
        words = [(x or b"").split() for x in texts]
        self._learn({w for ws in words for w in ws})
        out = []
        for ws in words:
            total = self.rows[np.fromiter(map(self.known.__getitem__, ws), np.int64, len(ws))].sum(0)
            if not total[-1]:
                out.append(("und", 0.0, total[:-1]))
                continue
            p = total[:-1] / total[-1]
            out.append((self.model.languages[int(p.argmax())], float(min(1.0, p.max())), p))
        return out


def train(docs: DataFrame, sample_docs: int = 1_500, sample_words: int = 24_000, hidden: int = 12, epochs: int = 10, lanes: int = 256) -> ByteGru | None:
    """Fit on about ``sample_docs`` documents of ``docs(doc_id, text, lang)`` (never over 5/4 of it).

    Of their distinct words at most ``sample_words`` (the most frequent) are used.  None
    if no document has a text and a language.
    """
    labelled = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull()).select("doc_id", "text", "lang")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seen: Counter = Counter()
            for text, lang in zip(byte_texts(batch.column("text")), batch.column("lang").to_pylist()):
                seen.update((part, lang) for w in set(text.split()) for part in _pieces(w))
            keys = list(seen)
            yield pa.RecordBatch.from_pydict({"word": pa.array([w for w, _ in keys], pa.binary()), "lang": pa.array([x for _, x in keys], pa.string()), "n": pa.array([seen[k] for k in keys], pa.int64())})

    sample = bounded_sample(labelled, "doc_id", sample_docs)
    words = materialise(sample.mapInArrow(count, "word binary, lang string, n long").groupBy("word", "lang").agg(F.sum("n").alias("n")), "sample-words")
    langs = sorted(x["lang"] for x in words.select("lang").distinct().collect())
    if not langs:
        return None
    shares = [F.sum(F.when(F.col("lang") == x, F.col("n")).otherwise(0)).alias(f"n{i}") for i, x in enumerate(langs)]
    # the most frequent words of each language, so that a frequent language does not crowd out the rest
    table = words.groupBy("word").agg(*shares, F.sum("n").alias("total"))
    picked = {}
    for i in range(len(langs)):
        for row in table.where(F.col(f"n{i}") > 0).orderBy(F.desc(f"n{i}"), F.xxhash64("word"), "word").limit(max(1, sample_words // len(langs))).collect():
            picked[bytes(row["word"])] = np.array([row[f"n{k}"] for k in range(len(langs))], np.float32)
    order = sorted(picked, key=lambda w: (len(w), w))
    total = np.sum([picked[w] for w in order], 0)
    model = ByteGru(langs, hidden)
    batches = []
    for n in sorted({len(w) for w in order if w}):
        same = [w for w in order if len(w) == n]
        np.random.default_rng(n).shuffle(same)
        for at in range(0, len(same), lanes):
            part = same[at : at + lanes]
            target = np.array([picked[w] / total for w in part], np.float32)
            target /= target.sum(1, keepdims=True)
            batches.append((_lanes(part), target, np.ones(len(part), np.float32)))
    model.fit(batches, epochs)
    return model


def identify(docs: DataFrame, model: ByteGru | None, margin: float = 1.2) -> DataFrame:
    """``docs`` with lang_pred, score (the pooled probability of lang_pred) and accepted.

    A text is accepted if it has a language whose probability is at least ``margin``
    times that of a guess among all learned ones.
    """
    floor = margin / len(model.languages) if model is not None and len(model.languages) > 1 else 0.0

    def make():
        labeller = DocumentLabeller(model) if model is not None else None

        def work(batch: pa.RecordBatch) -> list[pa.Array]:
            texts = byte_texts(batch.column("text"))
            got = labeller.label(texts) if labeller else [("und", 0.0)] * len(texts)
            fine = [x[0] != "und" and x[1] >= floor for x in got]
            return [pa.array([x[0] for x in got], pa.string()), pa.array([x[1] for x in got], pa.float64()), pa.array(fine, pa.bool_())]

        return work

    return with_columns(docs, "lang_pred string, score double, accepted boolean", make)


def learn_and_identify(docs: DataFrame, folds: int = 5, margin: float = 1.2, **options) -> DataFrame:
    """Train on the labelled rows outside fold 0 of the id's crc32 and label every row of ``docs``."""
    model = train(docs.where(id_bucket("doc_id", folds) != 0), **options)
    return identify(docs, model, margin).withColumn("held_out", id_bucket("doc_id", folds) == 0)
