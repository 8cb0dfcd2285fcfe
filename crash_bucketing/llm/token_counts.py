"""Token counts of byte-level byte-pair encoding by a whole-token shortcut.

Offline, every vocabulary string is put through the merges; those that come out as one token are proven whole. Texts
are cut into pre-tokens by the tokenizer's pattern, pre-tokens that are proven whole count one each, and only the
rest is merged (once for each different pre-token that a worker still remembers).
"""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator

import pyarrow as pa
import regex
import tiktoken
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_text

#: Fixed value: the pre-token pattern of byte-level vocabularies of this family.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
REMEMBERED = 400_000


def byte_names() -> dict[int, str]:
    """The printable character that stands for each byte in the vocabulary: printable Latin-1 bytes for themselves, others from 256 on."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in own]
    return {b: chr(b) for b in own} | {b: chr(256 + i) for i, b in enumerate(rest)}


class MergeTable:
    """Merge ranks over byte strings; count() gives the tokens of one pre-token."""

    def __init__(self, ranks: dict[tuple[bytes, bytes], int]):
        self.ranks = ranks

    def count(self, piece: bytes) -> int:
        parts = [piece[i : i + 1] for i in range(len(piece))]
        ranks = self.ranks
        while len(parts) > 1:
            least, at = min((ranks.get(pair, 1 << 30), i) for i, pair in enumerate(zip(parts, parts[1:], strict=False)))
            if least == 1 << 30:
                break
            left, right = parts[at], parts[at + 1]
            merged, i = [], 0
            while i < len(parts):
                if i + 1 < len(parts) and parts[i] == left and parts[i + 1] == right:
                    merged.append(left + right)
                    i += 2
                else:
                    merged.append(parts[i])
                    i += 1
            parts = merged
        return len(parts)


def load(path: str) -> tuple[dict[tuple[bytes, bytes], int], set[str], list[str]]:
    """(merge ranks, strings proven to encode alone as one token, special strings) of a tokenizer file."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    back = {name: byte for byte, name in byte_names().items()}
    raw = lambda s: bytes(back[c] for c in s)
    ranks = {}
    for i, m in enumerate(spec["model"]["merges"]):
        left, right = m if isinstance(m, list) else m.split(" ")
        ranks[raw(left), raw(right)] = i
    special = [t["content"] for t in spec["added_tokens"]]
    merges, whole = MergeTable(ranks), set()
    for name in spec["model"]["vocab"]:
        if name in special:
            continue
        piece = raw(name)
        if merges.count(piece) == 1:
            try:
                whole.add(piece.decode())
            except UnicodeDecodeError:  # part of a character: never a pre-token of its own
                pass
    return ranks, whole, special


class _Known(dict):
    """Tokens of a pre-token: one if proven whole, else merged and remembered (up to a bound)."""

    def __init__(self, whole: set[str], merge: Callable[[bytes], int]):
        super().__init__(dict.fromkeys(whole, 1))
        self.whole, self.merge = whole, merge

    def __missing__(self, piece: str) -> int:
        n = self.merge(piece.encode())
        if len(piece) <= 64:
            if len(self) > len(self.whole) + REMEMBERED:
                self.clear()
                self.update(dict.fromkeys(self.whole, 1))
            self[piece] = n
        return n


class TokenCounter:
    """Counts tokens of texts. The rest is merged by a compiled routine where ids follow the merge order, else by MergeTable."""

    def __init__(self, ranks: dict, whole: set[str], special: list[str], pattern: str = PATTERN):
        self.special = regex.compile("|".join(map(regex.escape, sorted(special, key=len, reverse=True)))) if special else None
        self.marks = special
        self.split = regex.compile(pattern).findall
        self.known = _Known(whole, compiled_merges(ranks) or MergeTable(ranks).count)

    def count(self, text: str) -> int:
        total, parts = 0, [text]
        if self.special and any(m in text for m in self.marks):
            parts = self.special.split(text)
            total = len(parts) - 1  # each special string is one token
        return total + sum(sum(map(self.known.__getitem__, self.split(part))) for part in parts)


def compiled_merges(ranks: dict[tuple[bytes, bytes], int]) -> Callable[[bytes], int] | None:
    """tiktoken's merge routine goes by the rank of the merged string: the same as the pair's if each string is made by one merge."""
    joined = {left + right: 256 + i for (left, right), i in ranks.items()}
    if len(joined) != len(ranks):
        return None
    core = tiktoken.Encoding("merges", pat_str=PATTERN, mergeable_ranks={bytes([b]): b for b in range(256)} | joined, special_tokens={})._core_bpe
    return lambda piece: len(core.encode_single_piece(piece))


_COUNTERS: dict[int, TokenCounter] = {}


def count_tokens(docs: DataFrame, tokenizer_path: str, limit: int = 1024) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_tokens, over_limit (n_tokens > limit).

    Counts are those of the tokenizer's library without begin, end or added tokens; special strings inside a text are one
    token. Null text is empty: zero bytes, zero tokens. Repeated rows give repeated results; an empty table gives an
    empty result. The file is read on the driver; its tables (50,000 strings and merges) are a broadcast of fixed size.
    """
    shared = docs.sparkSession.sparkContext.broadcast(load(tokenizer_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key = id(shared.value)
        if key not in _COUNTERS:  # one for all tasks of a worker
            _COUNTERS.clear()
            _COUNTERS[key] = TokenCounter(*shared.value)
        counter = _COUNTERS[key]
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("n_bytes"), pa.array([counter.count(t or "") for t in batch.column("text").to_pylist()], pa.int64())], names=["doc_id", "n_bytes", "n_tokens"])

    sized = id_text(docs).select("doc_id", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"), "text")
    return sized.mapInArrow(run, "doc_id long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)
