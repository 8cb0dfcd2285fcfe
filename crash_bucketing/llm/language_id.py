"""Language identification by a bidirectional gated recurrent network over bytes.

Two small recurrent layers read the bytes of a window from the left and from the right; at every position a softmax over
both states labels the byte, and the document's probabilities are the mean over all its positions. Trained in numpy by
backpropagation through time with a loss at every position. Gates and candidates use x / (1 + |x|) in place of the
sigmoid and the hyperbolic tangent, which numpy computes several times faster.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, held_out, id_text

WINDOW = 256
#: Columns of a step in prediction: keeps the working arrays in the processor's cache.
COLUMNS = 2048
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


class Layer:
    """One direction. Rows of w_in and u: update gate, reset gate, candidate (h of each)."""

    def __init__(self, hidden: int, rng: np.random.Generator):
        self.h = hidden
        self.w_in = (rng.standard_normal((3 * hidden, 256)) * 0.3).astype(np.float32)  # one column per byte value, bias included
        self.u = (rng.standard_normal((3 * hidden, hidden)) / np.sqrt(hidden)).astype(np.float32)

    def params(self) -> list[np.ndarray]:
        return [self.w_in, self.u]

    def forward(self, codes: np.ndarray, keep: bool = False):
        """codes: (time, columns). Yields the states (hidden, columns); keep: also what backpropagation needs."""
        n, h = codes.shape[1], self.h
        state = np.zeros((h, n), dtype=np.float32)
        x, a, d, c = (np.empty((k * h, n), dtype=np.float32) for k in (3, 3, 2, 1))
        for t in range(len(codes)):
            np.take(self.w_in, codes[t], axis=1, out=x, mode="clip")
            np.matmul(self.u, state, out=a)
            gates = x[: 2 * h] + a[: 2 * h]
            np.abs(gates, out=d)
            d += 1
            gates /= d
            gates *= 0.5
            gates += 0.5
            c = gates[h:] * a[2 * h :]
            c += x[2 * h :]
            scale = np.abs(c)
            scale += 1
            cand = c / scale
            new = cand - state
            new *= gates[:h]
            new += state
            yield (new, (state, gates, a[2 * h :].copy(), d.copy(), cand, scale)) if keep else new
            state = new

    def backward(self, codes: np.ndarray, saved: list, d_states: np.ndarray) -> list[np.ndarray]:
        """Gradients of w_in and u, from the loss gradients of all states (time, hidden, columns)."""
        h, g_in, g_u = self.h, np.zeros_like(self.w_in), np.zeros_like(self.u)
        carry = np.zeros_like(d_states[0])
        for t in range(len(codes) - 1, -1, -1):
            state, gates, uc, d, cand, scale = saved[t]
            g = d_states[t] + carry
            z, r = gates[:h], gates[h:]
            g_c = g * z / scale**2
            g_gates = np.concatenate([g * (cand - state), g_c * uc]) * 0.5 / d**2
            g_a = np.concatenate([g_gates, g_c * r])
            g_x = np.concatenate([g_gates, g_c])
            for k in range(len(g_x)):
                g_in[k] += np.bincount(codes[t], weights=g_x[k], minlength=256).astype(np.float32)
            g_u += g_a @ state.T
            carry = g * (1 - z) + self.u.T @ g_a
        return [g_in, g_u]


class ByteTagger:
    def __init__(self, languages: list[str], hidden: int = 8, seed: int = 11):
        rng = np.random.default_rng(seed)
        self.languages = languages
        self.layers = [Layer(hidden, rng), Layer(hidden, rng)]
        self.v = (rng.standard_normal((2, len(languages), hidden)) * 0.3).astype(np.float32)
        self.b = np.zeros((len(languages), 1), dtype=np.float32)

    def fit(self, texts: list[bytes], labels: list[int], steps: int = 220, length: int = 64, batch: int = 192, rate: float = 0.02, seed: int = 5) -> None:
        """Adam on random windows; every position carries the loss of its document's language."""
        rng = np.random.default_rng(seed)
        data = [np.frombuffer(t.translate(_LOWER), dtype=np.uint8) for t in texts]
        by = [[i for i, y in enumerate(labels) if y == k and len(data[i])] for k in range(len(self.languages))]
        by = [b for b in by if b]
        params = [p for layer in self.layers for p in layer.params()] + [self.v, self.b]
        first, second = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
        for step in range(1, steps + 1):
            codes = np.full((length, batch), 32, dtype=np.int64)
            y = np.zeros(batch, dtype=np.int64)
            for j in range(batch):
                i = by[j % len(by)][rng.integers(len(by[j % len(by)]))]
                at = rng.integers(max(1, len(data[i]) - length + 1))
                piece = data[i][at : at + length]
                codes[: len(piece), j] = piece
                y[j] = labels[i]
            saved = [list(layer.forward(c, keep=True)) for layer, c in zip(self.layers, (codes, codes[::-1]), strict=True)]
            left = np.stack([s for s, _ in saved[0]])
            right = np.stack([s for s, _ in saved[1]])[::-1]
            scores = self.v[0] @ left + self.v[1] @ right + self.b
            p = np.exp(scores - scores.max(axis=1, keepdims=True))
            p /= p.sum(axis=1, keepdims=True)
            p[:, y, np.arange(batch)] -= 1
            p /= length * batch
            g_v = np.stack([np.einsum("tlb,thb->lh", p, left), np.einsum("tlb,thb->lh", p, right)])
            back = [self.v[0].T @ p, (self.v[1].T @ p)[::-1]]
            grads = [g for layer, c, s, d in zip(self.layers, (codes, codes[::-1]), saved, back, strict=True) for g in layer.backward(c, [k for _, k in s], d)]
            for q, g, m, v in zip(params, [*grads, g_v, p.sum(axis=(0, 2))[:, None]], first, second, strict=True):
                m *= 0.9
                m += 0.1 * g
                v *= 0.995
                v += 0.005 * g * g
                q -= rate * (1 - step / (steps + 1)) * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.995**step)) + 1e-8)

    def positions(self, codes: np.ndarray) -> np.ndarray:
        """(time, languages, columns) probabilities of every byte of the windows (time, columns)."""
        n = len(codes)
        scores = np.empty((n, len(self.languages), codes.shape[1]), dtype=np.float32)
        for t, state in enumerate(self.layers[0].forward(codes)):
            np.matmul(self.v[0], state, out=scores[t])
        for t, state in enumerate(self.layers[1].forward(codes[::-1])):
            scores[n - 1 - t] += self.v[1] @ state
        scores += self.b
        scores -= scores.max(axis=1, keepdims=True)
        np.exp(scores, out=scores)
        scores /= scores.sum(axis=1, keepdims=True)
        return scores

    def documents(self, texts: list[bytes]) -> np.ndarray:
        """(texts, languages): mean of the position probabilities over all bytes of each text."""
        sums = np.zeros((len(texts), len(self.languages)))
        sizes = np.array([len(t) for t in texts])
        owner, columns = [], []
        for i, t in enumerate(texts):
            t = t.translate(_LOWER)
            for a in range(0, len(t), WINDOW):
                columns.append(t[a : a + WINDOW])
                owner.append(i)
                if len(columns) == COLUMNS:
                    self._add(columns, owner, sums)
                    owner, columns = [], []
        if columns:
            self._add(columns, owner, sums)
        return sums / np.maximum(sizes, 1)[:, None]

    def _add(self, columns: list[bytes], owner: list[int], sums: np.ndarray) -> None:
        """Windows are sorted by length into the same run, so short ones pad to the longest of their run only."""
        lengths = np.array([len(c) for c in columns])
        order = np.argsort(-lengths, kind="stable")
        full = int((lengths == WINDOW).sum())
        for part in (order[:full], order[full:]):
            if len(part):
                top = int(lengths[part].max())
                flat = b"".join(columns[i].ljust(top, b" ") for i in part)
                codes = np.ascontiguousarray(np.frombuffer(flat, dtype=np.uint8).reshape(len(part), top).T).astype(np.intp)
                p = self.positions(codes)
                p *= (np.arange(top)[:, None] < lengths[part][None, :])[:, None, :]
                np.add.at(sums, np.array(owner)[part], p.sum(axis=0).T)


def training_sample(docs: DataFrame, per_language: int, chars: int, max_languages: int = 1000) -> list[tuple[str, str]]:
    """(lang, text) of at most `per_language` rows a language that are not held out, from a place inside the text chosen by hash.

    One row a language comes to the driver, at most `max_languages` of them (checked).
    """
    rows = id_text(docs, F.col("lang").cast("string").alias("lang")).where(~held_out(F.col("doc_id")) & F.col("lang").isNotNull())
    rows = rows.withColumn("h", F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)))
    counts = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).limit(max_languages + 1).collect()}
    if len(counts) > max_languages:
        raise ValueError(f"more than {max_languages} languages")
    if not counts:
        return []
    some = F.coalesce(*[F.when(F.col("lang") == k, F.lit(min(1 << 30, int((1 << 30) * 2.0 * per_language / n) + 1))) for k, n in counts.items()])
    length = F.greatest(F.char_length("text") - chars, F.lit(1))
    picked = rows.where((F.col("h") < some) & F.col("text").isNotNull()).select("lang", "h", "doc_id", F.substring(F.col("text"), (F.pmod(F.xxhash64("doc_id", "lang"), length) + 1).cast("int"), F.lit(chars)).alias("text")).collect()
    out: list[tuple[str, str]] = []
    for k in sorted(counts):
        out += [(k, r["text"]) for r in sorted((r for r in picked if r["lang"] == k), key=lambda r: (r["h"], r["doc_id"] or 0))[:per_language]]
    return out


def identify_languages(docs: DataFrame, per_language: int = 400, sample_chars: int = 400) -> DataFrame:
    """One row per document: doc_id, held_out, lang_pred, score, second (the runner-up's probability).

    The network is fitted on at most `per_language` rows of each language, `sample_chars` characters of each, taken
    from rows that are not held out (crc32 of the id as text, modulo 5, not 0) and have a language; predictions read whole texts and nothing else. Null texts
    and texts without a letter are `und` with score 0, as is everything where there is nothing to learn from. Ties go to the first language by
    name; repeated rows give repeated results; an empty table gives an empty result.
    """
    sample = training_sample(docs, per_language, sample_chars)
    names = sorted({lang for lang, _ in sample})
    model = ByteTagger(names or ["und"])
    if names:
        model.fit([t.encode() for _, t in sample], [names.index(lang) for lang, _ in sample])
    shared = docs.sparkSession.sparkContext.broadcast((names, [layer.params() for layer in model.layers], model.v, model.b))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, layers, v, b = shared.value
        tagger = ByteTagger(names or ["und"])
        for layer, (w_in, u) in zip(tagger.layers, layers, strict=True):
            layer.w_in, layer.u = w_in, u
        tagger.v, tagger.b = v, b
        for batch in batches:
            texts = batch.column("text").to_pylist()
            known = [bool(names) and t is not None and any(map(str.isalpha, t)) for t in texts]
            p = tagger.documents([t or b"" for t in as_bytes(batch.column("text"))])
            top = p.argmax(axis=1)
            rest = p.copy()
            rest[np.arange(len(p)), top] = 0
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("held_out"), pa.array([tagger.languages[k] if on else "und" for k, on in zip(top, known, strict=True)], pa.string()), pa.array(np.where(known, np.clip(p.max(axis=1, initial=0), 0, 1), 0.0), pa.float64()), pa.array(np.where(known, rest.max(axis=1, initial=0), 0.0), pa.float64())],
                names=["doc_id", "held_out", "lang_pred", "score", "second"],
            )

    return id_text(docs, held_out(F.col("doc_id").cast("long"))).mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double, second double")
