"""Secret scans: fixed patterns, and a linear-chain conditional random field over the tokens of a text.

Tokens are runs of non-space characters. Each is described by its shape, the shapes of its two neighbours and features
of the whole file; three labels (begin, inside, outside) with learned transitions; decoding by Viterbi. The model is trained here,
by gradient ascent on the conditional likelihood (forward-backward in numpy), on seeded invented lines.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import id_text

#: The base patterns, in the order in which kinds are listed.
ASSIGN = re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
_STEMS = ("passw", "secret", "token", "apikey", "api_key")
KINDS = ("assign", "access", "hex", "crf")

OUT, BEGIN, INSIDE = 0, 1, 2


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """(kind, start, end) by start, then kind: leftmost non-overlapping matches of each kind, failing ones dropped."""
    low = text.lower()  # a key word in either case is in here too
    out = [("assign", *m.span()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6] if any(k in low for k in _STEMS) else []
    out += [("access", *m.span()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [("hex", *m.span()) for m in HEX.finditer(text)]  # a run of 24 or more: the same as all runs with the short ones dropped
    return sorted(out, key=lambda s: (s[1], KINDS.index(s[0])))


_PLAIN = re.compile(r"[^\W\d_]+(?:['’-][^\W\d_]+)*[.,;:!?)\]\"']*", re.UNICODE)
_WORD = re.compile(r"(password|passwd|pwd|secret|token|api[_-]?key|bearer|credential|authorization|private)", re.IGNORECASE | re.ASCII)
_CASE = re.compile(r"[a-z](?=[A-Z])|[A-Z](?=[a-z])")
_BODY = re.compile(r"^[\"'(<]*(.*?)[\"')>,;.]*$", re.DOTALL)


def shape(token: str) -> tuple[str, ...]:
    """Names of the features of one token; the empty tuple for plain words."""
    if _PLAIN.fullmatch(token) and len(token) < 24 and not _WORD.search(token) and (len(token) < 12 or len(_CASE.findall(token)) < 3):
        return ()
    body = _BODY.match(token)[1]
    tail = re.split(r"[=:]", body)[-1] if re.search(r"[=:]", body) else body
    out = [f"length{min(6, len(tail) // 6)}"]
    if key := _WORD.search(token):
        out.append("key")
        if key.end() >= len(body.rstrip("=:\"' ")):
            out.append("key_last")
    out += [n for n, p in (("sign_last", r"[=:]$"), ("only_sign", r"^[=:]+$"), ("sign_in", r"[=:].")) if re.search(p, body)]
    digits, lower, upper = (sum(f(c) for c in tail) for f in (str.isdigit, str.islower, str.isupper))
    n = max(1, len(tail))
    if re.fullmatch(r"[A-Za-z0-9+/_.=-]*", tail):
        out.append("safe")
        if len(tail) >= 12:
            counts = [tail.count(c) / n for c in set(tail)]
            out.append(f"entropy{int(-sum(p * math.log2(p) for p in counts))}")
            out += ["mixed"] if digits and lower and upper else ["digits_letters"] if digits and lower + upper else []
    if len(_CASE.findall(tail)) >= 3:
        out.append("case_changes")
    if re.fullmatch(r"[0-9a-f]{16,}", tail):
        out.append("hex")
    if re.match(r"(AKIA|ghp_|sk-|xox[bp]-|eyJ)", tail):
        out.append("known_prefix")
    out += [x for x, on in (("all_digits", digits == n), ("at", "@" in body), ("url", "://" in body), ("dashes", body.startswith("-----")), ("dashes_end", body.endswith("-----")), ("letters", lower + upper == n)) if on]
    return tuple(out)


def file_features(text: str) -> tuple[str, ...]:
    return tuple(x for x, on in (("has_key", bool(_WORD.search(text))), ("has_pem", "-----BEGIN" in text)) if on)


class Crf:
    """Weights: (feature, label) for own, previous, next and file features; transitions (label, label)."""

    def __init__(self, seed: int = 7, rounds: int = 80):
        sequences, labels = invented_lines(seed)
        self.index: dict[str, int] = {}
        shapes = [[shape(t) for t in s] for s in sequences]
        rows = [[self._active(a, i, file_features(" ".join(s)), grow=True) for i in range(len(a))] for a, s in zip(shapes, sequences, strict=True)]
        n, length, width = len(rows), len(rows[0]), len(self.index)
        x = np.zeros((n, length, width), dtype=np.float32)
        for i, r in enumerate(rows):
            for j, active in enumerate(r):
                x[i, j, active] = 1
        y = np.array(labels)
        gold = np.eye(3, dtype=np.float32)[y]
        pairs = np.einsum("nta,ntb->ab", gold[:, :-1], gold[:, 1:])
        w, trans = np.zeros((width, 3)), np.zeros((3, 3))
        ban = np.zeros((3, 3))
        ban[OUT, INSIDE] = -20.0  # inside never follows outside
        state = [np.zeros_like(a) for a in (w, w, trans, trans)]
        flat = x.reshape(-1, width)
        for step in range(1, rounds + 1):
            e, t = (flat @ w).reshape(n, length, 3), trans + ban
            a, b = np.zeros_like(e), np.zeros_like(e)
            a[:, 0] = e[:, 0]
            a[:, 0, INSIDE] -= 20
            for k in range(1, length):
                a[:, k] = e[:, k] + _lse(a[:, k - 1, :, None] + t, 1)
            for k in range(length - 2, -1, -1):
                b[:, k] = _lse(t + (e[:, k + 1] + b[:, k + 1])[:, None, :], 2)
            z = _lse(a[:, -1], 1)
            single = np.exp(a + b - z[:, None, None])
            double = np.exp(a[:, :-1, :, None] + t + (e + b)[:, 1:, None, :] - z[:, None, None, None]).sum(axis=(0, 1))
            for p, g, m, v in ((w, flat.T @ (gold - single).reshape(-1, 3) - 0.02 * w, state[0], state[1]), (trans, pairs - double - 0.02 * trans, state[2], state[3])):
                m *= 0.9
                m += 0.1 * g
                v *= 0.99
                v += 0.01 * g * g
                p += 0.2 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
        self._ready(w, trans + ban)

    def weights(self) -> tuple:
        return self.index, self.w, self.trans

    @classmethod
    def of(cls, weights: tuple) -> Crf:
        self = cls.__new__(cls)
        self.index = weights[0]
        self._ready(*weights[1:])
        return self

    def _ready(self, w: np.ndarray, trans: np.ndarray) -> None:
        self.w, self.trans = w, trans
        # how much the transitions can gain when one label differs from outside
        self.gain = max(self.trans[p, y] + self.trans[y, q] - self.trans[p, OUT] - self.trans[OUT, q] for p in range(3) for q in range(3) for y in (BEGIN, INSIDE) if self.trans[p, y] + self.trans[y, q] > -15 and self.trans[p, OUT] + self.trans[OUT, q] > -15)
        self.score = lru_cache(maxsize=200_000)(self._score)

    def _active(self, shapes: list, i: int, file: tuple[str, ...], grow: bool = False) -> list[int]:
        names = ["bias", *(f"own:{f}" for f in shapes[i] or ("plain",)), *(f"file:{f}" for f in file)]
        names += [f"prev:{f}" for f in (shapes[i - 1] or ("plain",)) if f in ("key", "key_last", "sign_last", "only_sign", "plain", "dashes", "dashes_end", "mixed", "length6")] if i else ["prev:none"]
        names += [f"next:{f}" for f in (shapes[i + 1] or ("plain",)) if f in ("plain", "dashes", "only_sign")] if i + 1 < len(shapes) else ["next:none"]
        return [self.index.setdefault(f, len(self.index)) for f in names] if grow else [self.index[f] for f in names if f in self.index]

    def _score(self, before: tuple | None, own: tuple, after: tuple | None, file: tuple) -> tuple[float, float, float]:
        """Scores of the three labels of a token, from its shape, its neighbours' and the file."""
        shapes = [s for s in (before, own, after) if s is not None]
        return tuple(self.w[self._active(shapes, 0 if before is None else 1, file)].sum(axis=0).tolist())

    def tag(self, shapes: list[tuple], file: tuple[str, ...]) -> list[tuple[int, int]]:
        """(first, last token) of the secrets, by Viterbi.

        A token whose outside score leads by more than transitions could ever gain is outside in the best path, whatever
        its neighbours are, so the chain falls apart there and only what lies between needs the dynamic programme.
        """
        n = len(shapes)
        odd = sorted({j for i, s in enumerate(shapes) if s for j in (i - 1, i, i + 1) if 0 <= j < n})
        open_ = []
        for i in odd:
            e = self.score(shapes[i - 1] if i else None, shapes[i], shapes[i + 1] if i + 1 < n else None, file)
            if e[OUT] - max(e[BEGIN], e[INSIDE]) <= self.gain:
                open_.append((i, e))
        out: list[tuple[int, int]] = []
        at = 0
        while at < len(open_):
            upto = at + 1
            while upto < len(open_) and open_[upto][0] == open_[upto - 1][0] + 1:
                upto += 1
            run = open_[at:upto]
            for k, label in enumerate(self.viterbi([e for _, e in run])):
                if label == BEGIN:
                    out.append((run[k][0], run[k][0]))
                elif label == INSIDE and out and out[-1][1] == run[k][0] - 1:
                    out[-1] = (out[-1][0], run[k][0])
            at = upto
        return out

    def viterbi(self, scores: list[tuple[float, float, float]]) -> list[int]:
        """Best labels of a run that stands between tokens that are outside."""
        t = self.trans.tolist()
        best, back = [t[OUT][y] + scores[0][y] for y in range(3)], []
        for e in scores[1:]:
            from_ = [max(range(3), key=lambda p: best[p] + t[p][y]) for y in range(3)]
            best = [best[from_[y]] + t[from_[y]][y] + e[y] for y in range(3)]
            back.append(from_)
        labels = [max(range(3), key=lambda y: best[y] + t[y][OUT])]
        for from_ in reversed(back):
            labels.append(from_[labels[-1]])
        return labels[::-1]


def _lse(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis=axis, keepdims=True)
    return np.squeeze(top, axis) + np.log(np.exp(x - top).sum(axis=axis))


def invented_lines(seed: int, n: int = 500, length: int = 20) -> tuple[list[list[str]], list[list[int]]]:
    """Seeded training lines of equal length: prose, numbers, addresses and junk outside; secrets in several settings."""
    rng = random.Random(seed)
    syllables = "an er on th in ou ti re he at en es or nt ea nd st ing ed ble ch le de ré öß ción mi ra ".split()
    base62 = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"

    def word() -> str:
        w = "".join(rng.choice(syllables) for _ in range(rng.randint(1, 5)))
        return (w.upper() if rng.random() < 0.1 else w.capitalize() if rng.random() < 0.15 else w) + rng.choice(["", "", "", "", ",", ".", "!!", "$$$", "***", "###", "%%%", "&&&", " |".strip()])

    def number() -> str:
        return rng.choice([str(rng.randint(0, 10**rng.randint(1, 12))), f"{rng.randint(1, 255)}.{rng.randint(0, 255)}.{rng.randint(0, 255)}.{rng.randint(1, 255)}", f"{word().strip('.,!$*#%&|')}.{rng.randint(1, 99)}@mail{rng.randint(1, 9)}.example.com", f"https://example.com/{word()}/{rng.randint(1, 999)}", f"20{rng.randint(10, 29)}-{rng.randint(10, 12)}-{rng.randint(10, 28)}", f"+{rng.randint(1, 99)}-{rng.randint(100, 999)}-{rng.randint(1000, 9999)}", f"{word()}={rng.randint(1, 99)}", f"{word()}:", "=", "|", "" + "".join(rng.choice("0123456789") for _ in range(16)), "-".join(word().strip(".,!$*#%&|") for _ in range(4)), "".join(word().strip(".,!$*#%&|") for _ in range(5)), "-".join("".join(rng.choice("0123456789abcdef") for _ in range(k)) for k in (8, 4, 4, 4, 12)), "".join(rng.choice("0123456789abcdef") for _ in range(rng.randint(6, 10)))])

    def value() -> str:
        return rng.choice([lambda: "".join(rng.choice(base62 + "+/_-") for _ in range(rng.randint(16, 44))), lambda: "".join(rng.choice("0123456789abcdef") for _ in range(rng.choice([24, 32, 40, 64]))), lambda: "AKIA" + "".join(rng.choice("ABCDEFGHIJKLMNOPQRSTUVWXYZ234567") for _ in range(16)), lambda: rng.choice(["ghp_", "sk-", "xoxb-"]) + "".join(rng.choice(base62) for _ in range(32))])()

    def secret() -> tuple[list[str], list[int]]:
        kind, key = rng.random(), rng.choice(["password", "passwd", "pwd", "secret", "token", "api_key", "apikey", "api-key", "AUTH_TOKEN", "client_secret"])
        q = rng.choice(["", '"', "'"])
        short = "".join(rng.choice(base62 + "!_-") for _ in range(rng.randint(8, 14)))
        v = q + (value() if rng.random() < 0.75 else short) + q
        if kind < 0.25:
            return [key, rng.choice("=:"), v], [OUT, OUT, BEGIN]
        if kind < 0.45:
            return [key + rng.choice(["=", ":"]) + v], [BEGIN]
        if kind < 0.6:
            return [key + ":", v], [OUT, BEGIN]
        if kind < 0.7:
            return ["Authorization:", "Bearer", value()], [OUT, OUT, BEGIN]
        if kind < 0.82:
            return [value()], [BEGIN]
        width = rng.choice([16, 24, 40, 64, 76])
        letters = rng.choice([base62 + "+/", base62 + "+/", base62[:52]])
        body = ["".join(rng.choice(letters) for _ in range(width)) for _ in range(rng.randint(1, 6))]
        body[-1] = body[-1][: rng.randint(8, width)] + rng.choice(["", "=", "=="])
        return ["-----BEGIN", "PRIVATE", "KEY-----", *body, "-----END", "PRIVATE", "KEY-----"], [OUT] * 3 + [BEGIN] + [INSIDE] * (len(body) - 1) + [OUT] * 3

    lines, labels = [], []
    for _ in range(n):
        tokens, marks = [], []
        while len(tokens) < length:
            r = rng.random()
            if r < 0.06:
                t, m = secret()
            elif r < 0.09:
                t, m = [rng.choice(["password", "token", "secret"]), word()], [OUT, OUT]
            else:
                t, m = [number() if r > 0.85 else word()], [OUT]
            tokens += t
            marks += m
        lines.append(tokens[:length])
        labels.append(marks[:length])
    return lines, labels


_TOKEN = re.compile(r"\S+")
#: A part that a base span leaves over counts if it holds so many letters or digits; less is a quote or a bracket.
LEFT_OVER = 4


def outside(text: str, start: int, end: int, base: list[tuple[str, int, int]]) -> list[tuple[int, int]]:
    """The parts of [start, end) that no base span covers, without blanks at their ends; the whole run where none meets it."""
    out, at = [], start
    for a, z in [*sorted((a, z) for _, a, z in base if a < end and start < z), (end, end)]:
        if a > at:
            part = text[at:a]
            left, right = at + len(part) - len(part.lstrip()), a - len(part) + len(part.rstrip())
            if (left, right) == (start, end) or sum(c.isalnum() for c in part) >= LEFT_OVER:
                out.append((left, right))
        at = max(at, z)
    return out


class SecretScanner:
    def __init__(self, crf: Crf):
        self.crf = crf
        self.shapes: dict[str, tuple] = {}

    def spans(self, text: str) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int]]]:
        """(base spans, all spans). Of a tagged run, what lies outside all base spans is added, part by part."""
        base = base_spans(text)
        tokens, known = text.split(), self.shapes
        if len(known) > 300_000:
            known.clear()
        key = bool(_WORD.search(text))
        odd: dict[str, tuple] = {}
        for t in set(tokens):
            if not key and len(t) < 24 and (t.isalpha() or t[:-1].isalpha() and t[-1] in ".,;:!?)]") and (len(t) < 12 or t.islower() or t.istitle()):
                continue  # plain, as shape() would say
            s = known.get(t)
            if s is None:
                s = known[t] = shape(t)
            if s:
                odd[t] = s
        if not odd:
            return base, base
        found = self.crf.tag([odd.get(t, ()) for t in tokens], file_features(text))
        more = []
        if found:
            places = [m.span() for m in _TOKEN.finditer(text)]
            for first, last in found:
                more += [("crf", a, z) for a, z in outside(text, places[first][0], places[last][1], base)]
        return base, sorted(base + more, key=lambda s: (s[1], KINDS.index(s[0])))


def scan_secrets(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, n_assign, n_access, n_hex, base_sha256, spans.

    spans: kind:start:end in code points, end exclusive, by start then kind, comma-joined; base_sha256 is the digest of the base ones
    alone. Null text is empty: no spans. Repeated rows give repeated results; whole texts of any length are read; an empty
    table gives an empty result.
    """

    model = docs.sparkSession.sparkContext.broadcast(Crf().weights())  # trained once, a few thousand numbers

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = SecretScanner(Crf.of(model.value))
        join = lambda spans: ",".join(f"{k}:{a}:{z}" for k, a, z in spans)
        for batch in batches:
            found = [scanner.spans(t or "") for t in batch.column("text").to_pylist()]
            counts = [pa.array([sum(s[0] == k for s in base) for base, _ in found], pa.int64()) for k in KINDS[:3]]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *counts, pa.array([hashlib.sha256(join(base).encode()).hexdigest() for base, _ in found], pa.string()), pa.array([join(every) for _, every in found], pa.string())], names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])

    return id_text(docs).mapInArrow(run, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")
