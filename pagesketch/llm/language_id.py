"""Language identification by a bidirectional gated recurrent network over bytes, trained in numpy.

Backpropagation through time runs over windows of the lower-cased UTF-8 bytes of whole texts, those of a bounded sample of labelled rows.
To predict, each whole text is cut into windows that both directions enter and leave through a margin of neighbouring bytes; every byte
position gets probabilities, and their mean over all positions is the document's.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pagesketch.llm.common import CHUNK_BYTES, chunks, crc_of_id

#: Bytes of a window in training and prediction, of the margin on both sides in prediction; hidden units of each direction.
TRAIN_STEPS, STEPS, MARGIN, HIDDEN = 64, 512, 16, 12
#: Windows that run side by side.
BLOCK = 1024
#: Most labelled rows of a language that are learned from, whole. Rows of more characters are not drawn, since the driver holds the sample.
ROWS_PER_LANGUAGE, LONGEST_DRAWN = 400, 200_000
PAD = 256
UNKNOWN = "und"


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


@dataclass
class Direction:
    """Weights of one direction: byte table (gates update, reset, candidate) and recurrent ones."""

    table: np.ndarray
    gates: np.ndarray
    candidate: np.ndarray

    @staticmethod
    def start(rng: np.random.Generator, hidden: int) -> Direction:
        draw = lambda *shape, scale: (rng.standard_normal(shape) * scale).astype(np.float32)
        return Direction(draw(257, 3 * hidden, scale=0.3), draw(hidden, 2 * hidden, scale=hidden**-0.5), draw(hidden, hidden, scale=hidden**-0.5))

    def arrays(self) -> list[np.ndarray]:
        return [self.table, self.gates, self.candidate]

    def run(self, ids: np.ndarray, keep: list | None = None) -> np.ndarray:
        """Hidden states (steps, windows, hidden) of byte ids (steps, windows)."""
        steps, n = ids.shape
        size = self.candidate.shape[0]
        out = np.empty((steps, n, size), np.float32)
        h = np.zeros((n, size), np.float32)
        for t in range(steps):
            x = self.table[ids[t]]
            gate = _sigmoid(x[:, : 2 * size] + h @ self.gates)
            z, r = gate[:, :size], gate[:, size:]
            c = np.tanh(x[:, 2 * size :] + (r * h) @ self.candidate)
            new = h + z * (c - h)
            if keep is not None:
                keep.append((h, z, r, c))
            h = out[t] = new
        return out

    def back(self, ids: np.ndarray, kept: list, grad: np.ndarray) -> list[np.ndarray]:
        """Gradients of the weights from those of all hidden states, through time."""
        size = self.candidate.shape[0]
        d_table, d_gates, d_candidate = (np.zeros_like(a) for a in self.arrays())
        carry = np.zeros_like(kept[0][0])
        for t in range(len(kept) - 1, -1, -1):
            h, z, r, c = kept[t]
            g = grad[t] + carry
            d_c = g * z * (1 - c * c)
            d_z = g * (c - h) * z * (1 - z)
            d_rh = d_c @ self.candidate.T
            d_r = d_rh * h * r * (1 - r)
            d_gate = np.concatenate([d_z, d_r], axis=1)
            carry = g * (1 - z) + d_rh * r + d_gate @ self.gates.T
            d_candidate += (r * h).T @ d_c
            d_gates += h.T @ d_gate
            d_x = np.concatenate([d_gate, d_c], axis=1)
            order = np.argsort(ids[t], kind="stable")
            own = ids[t][order]
            first = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]]))
            d_table[own[first]] += np.add.reduceat(d_x[order], first)
        return [d_table, d_gates, d_candidate]


class ByteGru:
    """Two directions and a softmax over their states at every position."""

    def __init__(self, languages: list[str], hidden: int = HIDDEN, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.languages, self.rng = languages, rng
        self.forward, self.backward = Direction.start(rng, hidden), Direction.start(rng, hidden)
        self.out = (rng.standard_normal((2 * hidden, len(languages))) * 0.1).astype(np.float32)
        self.bias = np.zeros(len(languages), np.float32)

    def arrays(self) -> list[np.ndarray]:
        return [*self.forward.arrays(), *self.backward.arrays(), self.out, self.bias]

    def states(self, ids: np.ndarray, keep: tuple[list, list] | None = None) -> np.ndarray:
        a = self.forward.run(ids, keep and keep[0])
        b = self.backward.run(ids[::-1], keep and keep[1])[::-1]
        return np.concatenate([a, b], axis=2)

    def probabilities(self, ids: np.ndarray, states: np.ndarray | None = None) -> np.ndarray:
        """(steps, windows, languages) for byte ids (steps, windows)."""
        x = (self.states(ids) if states is None else states) @ self.out + self.bias
        x -= x.max(axis=2, keepdims=True)
        np.exp(x, out=x)
        x /= x.sum(axis=2, keepdims=True)
        return x

    def gradients(self, ids: np.ndarray, labels: np.ndarray) -> tuple[float, list[np.ndarray]]:
        """Mean cross entropy over real positions, and its gradients."""
        keep: tuple[list, list] = ([], [])
        states = self.states(ids, keep)
        p = self.probabilities(ids, states)
        real = (ids != PAD).astype(np.float32)
        n = max(1.0, float(real.sum()))
        at = np.arange(ids.shape[1])
        loss = -float((np.log(p[:, at, labels] + 1e-9) * real).sum()) / n
        p[:, at, labels] -= 1
        p *= (real / n)[:, :, None]
        flat = states.reshape(-1, states.shape[2])
        grads = [flat.T @ p.reshape(-1, p.shape[2]), p.sum(axis=(0, 1))]
        g = p @ self.out.T
        size = g.shape[2] // 2
        return loss, [*self.forward.back(ids, keep[0], g[:, :, :size]), *self.backward.back(ids[::-1], keep[1], g[::-1, :, size:]), *grads]

    def fit(self, ids: np.ndarray, labels: np.ndarray, rounds: int = 400, batch: int = 192, rate: float = 0.01) -> ByteGru:
        """Adam over random batches with as many windows of each language."""
        weights = self.arrays()
        m, v = [np.zeros_like(w) for w in weights], [np.zeros_like(w) for w in weights]
        pools = [np.flatnonzero(labels == k) for k in range(len(self.languages))]
        pools = [p for p in pools if len(p)]
        for step in range(1, rounds + 1):
            pick = np.concatenate([self.rng.choice(p, max(1, batch // len(pools))) for p in pools])
            _, grads = self.gradients(ids[:, pick], labels[pick])
            norm = np.sqrt(sum(float((g * g).sum()) for g in grads))
            scale = min(1.0, 1.0 / (norm + 1e-9))
            pace = rate * (1 - 0.9 * step / rounds)
            for w, g, a, b in zip(weights, grads, m, v, strict=True):
                g = g * scale
                a += 0.1 * (g - a)
                b += 0.01 * (g * g - b)
                w -= pace * (a / (1 - 0.9**step)) / (np.sqrt(b / (1 - 0.99**step)) + 1e-8)
        return self


def window_ids(raw: list[bytes], steps: int) -> tuple[np.ndarray, np.ndarray]:
    """Byte ids (steps, windows) of the texts, padded at their ends, and the text of every window."""
    sizes = np.array([len(r) for r in raw], np.int64)
    counts = -(-sizes // steps)
    first = np.concatenate([[0], np.cumsum(counts)])
    out = np.full(int(first[-1]) * steps, PAD, np.int16)
    data = np.frombuffer(b"".join(raw), np.uint8)
    shift = np.repeat(first[:-1] * steps - np.concatenate([[0], np.cumsum(sizes)[:-1]]) if len(sizes) else first[:0], sizes)
    out[np.arange(len(data)) + shift] = data
    return out.reshape(-1, steps).T, np.repeat(np.arange(len(raw)), counts)


def lowered(text: str | None) -> bytes:
    return (text or "").lower().encode("utf-8", "replace")


def has_letter(text: str | None) -> bool:
    return bool(text) and any(map(str.isalpha, text))


def training_texts(docs: DataFrame, allowed: Column, id_col: str, text_col: str, lang_col: str, rows: int = ROWS_PER_LANGUAGE) -> list[tuple[str, str]]:
    """(language, whole text) of at most rows labelled rows of each language: those with the smallest hashes of their ids."""
    labelled = docs.where(allowed & F.col(lang_col).isNotNull() & (F.length(F.trim(text_col)) > 0) & (F.length(text_col) <= LONGEST_DRAWN))
    rank = F.pmod(F.xxhash64(F.col(id_col).cast("string"), F.lit("row")), F.lit(1 << 30))
    counts = labelled.groupBy(F.col(lang_col).alias("lang")).count()
    picked = labelled.select(F.col(lang_col).alias("lang"), rank.alias("rank"), F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    # a share of the hash range that holds twice the wanted rows; tiny languages are taken whole
    share = F.least(F.lit(1.0), F.lit(2.0 * rows) / F.col("count"))
    near = picked.join(F.broadcast(counts), "lang").where(F.col("rank") / float(1 << 30) < share)
    near = near.groupBy("lang", "rank", "id").agg(F.min("text").alias("text"))  # a repeated id counts once
    place = F.row_number().over(Window.partitionBy("lang").orderBy("rank", "id"))
    found = near.withColumn("place", place).where(F.col("place") <= rows).orderBy("lang", "place").collect()
    return [(r["lang"], r["text"]) for r in found]


def train(texts: list[tuple[str, str]]) -> ByteGru | None:
    """Learns from all windows of the texts, and from every third once more with its end padded, so that short texts are learned too."""
    if not texts:
        return None
    languages = sorted({lang for lang, _ in texts})
    ids, owner = window_ids([lowered(text) for _, text in texts], TRAIN_STEPS)
    if not len(owner):
        return None
    labels = np.array([languages.index(lang) for lang, _ in texts])[owner]
    short = ids[:, ::3].copy()
    sizes = 8 + np.arange(short.shape[1]) * 37 % (TRAIN_STEPS - 8)
    short[np.arange(TRAIN_STEPS)[:, None] >= sizes] = PAD
    some = (short != PAD).any(axis=0)
    return ByteGru(languages).fit(np.hstack([ids, short[:, some]]), np.concatenate([labels, labels[::3][some]]))


def centred_windows(sizes: np.ndarray, steps: int = STEPS, margin: int = MARGIN) -> tuple[np.ndarray, ...]:
    """Windows of texts that lie end to end: the text of each, first byte, bytes before the centre, after the centre's end, and in all; long windows first."""
    counts = -(-sizes // steps)
    owner = np.repeat(np.arange(len(sizes)), counts)
    low = (np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts)) * steps
    high = np.minimum(low + steps, sizes[owner])
    first, last = np.maximum(low - margin, 0), np.minimum(high + margin, sizes[owner])
    order = np.argsort(first - last, kind="stable")
    begin = (np.cumsum(sizes) - sizes)[owner]
    return tuple(x[order] for x in (owner, begin + first, low - first, high - first, last - first))


class Stepper:
    """One direction, laid out to step many windows at once.

    Each gate has arrays of its own, so that all are contiguous, and the weights are scaled so that a gate takes one exponential:
    1 / (1 + exp(-x)) for update and reset, 1 - 2 / (1 + exp(2 x)) for the candidate. The states are those of Direction.run.
    """

    def __init__(self, direction: Direction, out: np.ndarray):
        update, reset, candidate = (np.ascontiguousarray(x) for x in np.split(direction.table, 3, axis=1))
        self.tables = [-update, -reset, 2 * candidate]
        self.gates = -np.stack(np.split(direction.gates, 2, axis=1))
        self.candidate = 2 * direction.candidate
        self.out = np.ascontiguousarray(out.T)

    def start(self, n: int) -> None:
        size = len(self.candidate)
        self.h, self.c = np.zeros((n, size), np.float32), np.empty((n, size), np.float32)
        self.x, self.gate = np.empty((3, n, size), np.float32), np.empty((2, n, size), np.float32)

    def step(self, ids: np.ndarray) -> np.ndarray:
        """What the direction adds to the logits (languages, windows), after a byte more of the first windows."""
        m = len(ids)
        h, c, x, gate = self.h[:m], self.c[:m], self.x[:, :m], self.gate[:, :m]
        for rows, own in zip(self.tables, x, strict=True):
            rows.take(ids, axis=0, out=own, mode="clip")
        np.matmul(h, self.gates, out=gate)
        gate += x[:2]
        np.exp(gate, out=gate)
        gate += 1
        z, r = gate
        np.divide(h, r, out=r)
        np.matmul(r, self.candidate, out=c)
        c += x[2]
        np.exp(c, out=c)
        c += 1
        np.divide(-2, c, out=c)
        c += 1
        c -= h
        c /= z
        h += c
        return self.out @ h.T


def pooled(net: ByteGru, raw: list[bytes]) -> np.ndarray:
    """Mean probabilities over all positions of each text; every position is labelled once, in its window's centre.

    Windows are as long as their texts make them: a shorter one ends forward, and begins backward, at its own last byte, whatever lies beside it.
    """
    sizes = np.array([len(x) for x in raw], np.int64)
    data = np.frombuffer(b"".join(raw), np.uint8).astype(np.intp)
    sums = np.zeros((len(raw), len(net.languages)))
    hidden = len(net.out) // 2
    forward, backward = Stepper(net.forward, net.out[:hidden]), Stepper(net.backward, net.out[hidden:])
    windows = centred_windows(sizes)
    for lo in range(0, len(windows[0]), BLOCK):
        owner, begin, low, high, length = (x[lo : lo + BLOCK] for x in windows)
        n, steps = len(owner), int(length[0])
        live = np.searchsorted(-length, -np.arange(steps))  # windows that reach a step; long ones come first
        logits = np.empty((steps, len(net.languages), n), np.float32)
        total = np.zeros((len(net.languages), n))
        forward.start(n)
        backward.start(n)
        with np.errstate(over="ignore"):  # a closed gate is divided by infinity
            for t in range(steps):
                m = live[t]
                logits[t, :, :m] = forward.step(data.take(begin[:m] + t))
            for t in range(steps - 1, -1, -1):
                m = live[t]
                p = backward.step(data.take(begin[:m] + t))
                p += logits[t, :, :m]
                p += net.bias[:, None]
                p -= p.max(axis=0)
                np.exp(p, out=p)
                p *= ((t >= low[:m]) & (t < high[:m])) / p.sum(axis=0)
                total[:, :m] += p
        for k, x in enumerate(total):
            sums[:, k] += np.bincount(owner, x, len(raw))
    return sums / np.maximum(sizes, 1)[:, None]


def predict(docs: DataFrame, model: ByteGru | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, lang_pred and score of every row; every position of the whole text is labelled."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        net = shared.value
        for batch in batches:
            for part in chunks(batch, "text", CHUNK_BYTES):
                texts = part.column("text").to_pylist()
                letters = [has_letter(t) for t in texts]
                names, scores = [UNKNOWN] * len(texts), np.zeros(len(texts))
                ask = [i for i, x in enumerate(letters) if x and net is not None]
                if ask:
                    mean = pooled(net, [lowered(texts[i]) for i in ask])
                    best = mean.argmax(axis=1)
                    for j, i in enumerate(ask):
                        names[i], scores[i] = net.languages[best[j]], min(1.0, max(0.0, float(mean[j, best[j]])))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("held_out"), pa.array(names, pa.string()), pa.array(scores)], ["doc_id", "held_out", "lang_pred", "score"])

    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.pmod(crc_of_id(F.col(id_col)), F.lit(4)) == 2, F.lit(False)).alias("held_out"), F.col(text_col).alias("text"))
    kind = rows.schema["doc_id"].dataType.simpleString()
    return rows.mapInArrow(run, f"doc_id {kind}, held_out boolean, lang_pred string, score double")


def identify(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """Languages of all rows by a network that learned from those that are not held out.

    A row is held out if crc32 of its id as text is 2 modulo 4; a null id is not. Rows with a null language are predicted only. A text that is null or
    has no letter is 'und' with score 0, as is every row if nothing could be learned. Repeated rows get repeated results.
    """
    allowed = F.coalesce(F.pmod(crc_of_id(F.col(id_col)), F.lit(4)) != 2, F.lit(False))
    texts = training_texts(docs.select(id_col, text_col, lang_col), allowed, id_col, text_col, lang_col)
    return predict(docs, train(texts), id_col, text_col)
