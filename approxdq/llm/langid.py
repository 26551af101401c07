"""Language of a text: a bidirectional gated recurrent network over its bytes, in NumPy.

Training (on the driver): at most ``per_lang`` labelled documents of each language, those of the smallest hash
of doc_id (at most ``most_langs`` languages), and of each a stretch of ``stretch`` characters at a hashed place; both bounds are parameters.
Back-propagation through time with Adam from fixed seeds, so the model depends on the sample alone.

Prediction: every byte of the whole text is read, in segments of ``SEGMENT`` bytes; the network has a state for
each byte from the left and one from the right within its segment, and gives each position probabilities of the
languages. A document's probabilities are the mean over its positions; ties go to the earlier language name.

A null text, or one without a letter, is ``und`` with score 0; so is any text if no labelled row exists.
Repeated rows get equal answers. lang, source and doc_id are not inputs of a prediction.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import common as C

SEGMENT, UNITS = 96, 8


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + 0.5


class ByteGRU:
    """x: bytes (B, T); the second direction reads from the right."""

    def __init__(self, langs: list[str], units: int = UNITS, seed: int = 0):
        r = np.random.default_rng(seed)
        f = lambda *shape, s: (r.normal(size=shape) * s).astype(np.float32)
        self.langs, self.units = langs, units
        self.p = {"in": f(2, 256, 3 * units, s=0.3), "rec": f(2, units, 3 * units, s=0.3), "out": f(2 * units, len(langs), s=0.3), "bias": np.zeros(len(langs), np.float32)}

    def states(self, x: np.ndarray, keep: list | None = None) -> np.ndarray:
        """(T, B, 2 * units): state at each position, left then right."""
        p, h_n = self.p, self.units
        size, steps = x.shape
        h = np.zeros((2, size, h_n), np.float32)
        out = np.empty((steps, size, 2 * h_n), np.float32)
        columns = np.ascontiguousarray(x.T)
        a = np.empty((2, size, 3 * h_n), np.float32)
        for t in range(steps):
            np.take(p["in"][0], columns[t], axis=0, out=a[0], mode="clip")
            np.take(p["in"][1], columns[steps - 1 - t], axis=0, out=a[1], mode="clip")
            u = np.matmul(h, p["rec"])
            gates = a[..., : 2 * h_n] + u[..., : 2 * h_n]
            gates *= 0.5
            np.tanh(gates, out=gates)
            gates *= 0.5
            gates += 0.5
            z, reset = gates[..., :h_n], gates[..., h_n:]
            inner = u[..., 2 * h_n :]
            n = reset * inner
            n += a[..., 2 * h_n :]
            np.tanh(n, out=n)
            if keep is not None:
                keep.append((h, z, reset, n, inner))
            h = n + z * (h - n)
            out[t, :, :h_n] = h[0]
            out[steps - 1 - t, :, h_n:] = h[1]
        return out

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        """(T, B, languages)"""
        logits = self.states(x) @ self.p["out"]
        logits += self.p["bias"]
        logits -= logits.max(-1, keepdims=True)
        np.exp(logits, out=logits)
        logits /= logits.sum(-1, keepdims=True)
        return logits

    def gradients(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Loss of every position against its segment's language, and the gradient of each parameter."""
        p, h_n, kept = self.p, self.units, []
        size, steps = x.shape
        states = self.states(x, kept)
        logits = states @ p["out"] + p["bias"]
        logits -= logits.max(-1, keepdims=True)
        prob = np.exp(logits)
        prob /= prob.sum(-1, keepdims=True)
        w = (weight / max(1.0, weight.sum())).T[..., None].astype(np.float32)
        loss = float(-(np.log(np.maximum(prob[:, np.arange(size), y], 1e-9)) * w[..., 0]).sum())
        d = prob.copy()
        d[:, np.arange(size), y] -= 1
        d *= w
        grads = {"out": states.reshape(-1, 2 * h_n).T @ d.reshape(-1, d.shape[-1]), "bias": d.sum((0, 1))}
        d_states = d @ p["out"].T
        rec = np.zeros_like(p["rec"])
        d_in = np.empty((2, steps, size, 3 * h_n), np.float32)
        dh = np.zeros((2, size, h_n), np.float32)
        for t in range(steps - 1, -1, -1):
            h, z, reset, n, inner = kept[t]
            dh = dh + np.stack([d_states[t, :, :h_n], d_states[steps - 1 - t, :, h_n:]])
            dn = dh * (1 - z) * (1 - n * n)
            dz = dh * (h - n) * z * (1 - z)
            dr = dn * inner * reset * (1 - reset)
            d_in[:, t] = np.concatenate([dz, dr, dn], -1)
            du = np.concatenate([dz, dr, dn * reset], -1)
            rec += np.matmul(h.transpose(0, 2, 1), du)
            dh = dh * z + np.matmul(du, p["rec"].transpose(0, 2, 1))
        grads["rec"], grads["in"] = rec, np.zeros_like(p["in"])
        for k, seen in enumerate((x.T, x.T[::-1])):
            order = np.argsort(seen.ravel(), kind="stable")
            byte = seen.ravel()[order]
            starts = np.flatnonzero(np.append(True, byte[1:] != byte[:-1]))
            grads["in"][k, byte[starts]] = np.add.reduceat(d_in[k].reshape(-1, 3 * h_n)[order], starts)
        return loss, grads

    def train(self, texts: list[bytes], labels: list[int], steps: int = 220, batch: int = 192, length: int = 48, rate: float = 0.03, seed: int = 1) -> ByteGRU:
        """Adam on random segments; each language is drawn equally often."""
        r = np.random.default_rng(seed)
        by_lang = [[t for t, y in zip(texts, labels, strict=True) if y == k and t] for k in range(len(self.langs))]
        able = [k for k, own in enumerate(by_lang) if own]
        moments = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in self.p.items()}
        for step in range(1, steps + 1) if able else ():
            x, weight, y = np.zeros((batch, length), np.uint8), np.zeros((batch, length), np.float32), np.array([able[i % len(able)] for i in range(batch)])
            for i, k in enumerate(y):
                t = by_lang[k][r.integers(len(by_lang[k]))]
                at = int(r.integers(max(1, len(t) - length + 1)))
                part = np.frombuffer(t[at : at + length], np.uint8)
                x[i, : len(part)], weight[i, : len(part)] = part, 1
            _, grads = self.gradients(x, y, weight)
            norm = np.sqrt(sum(float((g * g).sum()) for g in grads.values()))
            for k, g in grads.items():
                g = g * min(1.0, 1.0 / (norm + 1e-9))
                m, v = moments[k]
                m += 0.1 * (g - m)
                v += 0.01 * (g * g - v)
                self.p[k] -= (rate * (1 - step / (steps + 1)) * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)).astype(np.float32)
        return self

    def pooled(self, data: np.ndarray, offsets: np.ndarray, block: int = 1024) -> np.ndarray:
        """Mean probabilities over all bytes of each row."""
        lengths = np.diff(offsets)
        n_seg = -(-lengths // SEGMENT)
        row = np.repeat(np.arange(len(lengths)), n_seg)
        start = offsets[row] + SEGMENT * (np.arange(len(row)) - np.repeat(np.cumsum(n_seg) - n_seg, n_seg))
        size = np.minimum(SEGMENT, offsets[row + 1] - start)
        padded = np.concatenate([data, np.zeros(SEGMENT, np.uint8)])
        sums = np.zeros((len(lengths), len(self.langs)))
        steps = np.arange(SEGMENT)
        for a in range(0, len(row), block):
            own = slice(a, a + block)
            x = padded[start[own, None] + steps]
            inside = steps < size[own, None]
            prob = self.probabilities(np.where(inside, x, 0))
            prob *= inside.T[..., None]
            np.add.at(sums, row[own], prob.sum(0))
        return sums / np.maximum(lengths, 1)[:, None]


def held_out() -> F.Column:
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0


def fit(docs: DataFrame, per_lang: int = 400, stretch: int = 3000, steps: int = 500, most_langs: int = 256) -> ByteGRU | None:
    """A model from labelled rows that aren't held out; None without any. Only languages of such rows are learnt, the
    ``most_langs`` of most rows. Rows are counted by language first, which gives each a bar on the hash that about twice
    ``per_lang`` rows pass; only these are shuffled, so a hot language costs as much as any other."""
    doc = F.col("doc_id").cast("string")
    at = F.lit(1) + F.pmod(F.xxhash64(F.lit("place"), doc), F.greatest(F.lit(1), F.char_length("text") - stretch))
    able = docs.where(F.col("text").isNotNull() & F.col("lang").isNotNull() & ~F.coalesce(held_out(), F.lit(False)))
    sizes = able.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "lang").limit(most_langs).collect()
    if not sizes:
        return None
    bars = [(r.lang, (1 << 63) - 1 if r.n <= 2 * per_lang else int(2 * per_lang / r.n * 2.0**64) - (1 << 63)) for r in sizes]
    bar = docs.sparkSession.createDataFrame(bars, "lang string, bar long")
    own = able.select(F.col("lang").cast("string").alias("lang"), F.xxhash64(doc).alias("key"), F.col("text").substr(at, F.lit(stretch)).alias("text"))
    own = own.join(F.broadcast(bar), "lang").where("key <= bar").select("lang", "key", "text").distinct()
    place = F.row_number().over(Window.partitionBy("lang").orderBy("key", "text"))
    rows = sorted(own.withColumn("place", place).where(F.col("place") <= per_lang).select("lang", "key", "text").collect())
    langs = sorted({r.lang for r in rows})
    return ByteGRU(langs).train([r.text.encode() for r in rows], [langs.index(r.lang) for r in rows], steps=steps)


_OUT = pa.schema([("doc_id", pa.int64()), ("lang_pred", pa.string()), ("score", pa.float64())])


class Guesser:
    """Language and score of each text of a column."""

    def __init__(self, langs: list[str], p: dict[str, np.ndarray]):
        self.net = ByteGRU(langs)
        self.net.p = p

    def guess(self, column) -> tuple[list[str], np.ndarray]:
        letter = pc.fill_null(pc.match_substring_regex(column, r"\p{L}"), False).to_numpy(zero_copy_only=False)
        prob = self.net.pooled(*C.flat(column))
        best = prob.argmax(1)
        score = np.clip(np.where(letter, prob[np.arange(len(best)), best], 0.0), 0.0, 1.0)
        return [self.net.langs[b] if ok else "und" for b, ok in zip(best, letter, strict=True)], score


def predict(docs: DataFrame, model: ByteGRU | None) -> DataFrame:
    """One row per document: doc_id, lang_pred, score."""
    own = C.documents(docs)
    if model is None:
        return own.select("doc_id", F.lit("und").alias("lang_pred"), F.lit(0.0).alias("score"))
    shared = docs.sparkSession.sparkContext.broadcast((model.langs, model.p))

    def work(piece: pa.RecordBatch) -> pa.RecordBatch:
        lang, score = Guesser(*shared.value).guess(piece.column("text"))
        return pa.RecordBatch.from_arrays([piece.column("doc_id"), pa.array(lang, pa.string()), pa.array(score)], schema=_OUT)

    return C.map_pieces(own, work, "doc_id long, lang_pred string, score double")


def identified(docs: DataFrame, **bounds) -> DataFrame:
    """held_out, lang_pred and score of each document, by a model learnt from the rest."""
    flags = predict(docs, fit(docs, **bounds))
    return flags.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "lang_pred", "score")


def accepted(docs: DataFrame, least: float = 0.3, **bounds) -> DataFrame:
    """Documents whose language is known with at least this score; the others are rejected. Each row is judged by its own
    text in one narrow pass that carries all its columns."""
    model = fit(docs, **bounds)
    if model is None:
        return docs.where(F.lit(False))
    C.ship(docs.sparkSession)
    shared, at = docs.sparkSession.sparkContext.broadcast((model.langs, model.p)), docs.columns.index("text")

    def work(piece: pa.RecordBatch) -> pa.RecordBatch:
        lang, score = Guesser(*shared.value).guess(piece.column(at))
        return piece.filter(pa.array([x != "und" and s >= least for x, s in zip(lang, score.tolist(), strict=True)], pa.bool_()))

    return C.map_pieces(docs, work, docs.schema)
