"""Byte-pair encoding and decoding of whole texts, exact to the merge order, in linear time.

The encoder walks a word left to right and always tries the longest vocabulary token that starts there (all tokens of a
word come from one Aho-Corasick pass). A token may follow another only if the merge rules would not have joined bytes
across the border; that is looked up pair by pair. When no token fits, the encoder steps back and shortens the last
one; positions known to fail are marked, so each is entered once. Words repeat, so results are kept by word in a
table of bounded size. Decoding gathers token bytes through an offset table.
"""

from __future__ import annotations

import hashlib
import json
import struct
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavefront.llm.workers import give_back, held, small_batches

# The word pattern of the vocabulary's byte-level splitter, with white space spelled out.
_WS = r"\t-\r \x85\xa0  -     　"
WORD_PATTERN = rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{_WS}\p{{L}}\p{{N}}]+|[{_WS}]+(?![^{_WS}])|[{_WS}]+"
KEPT_WORDS = 150_000
KEPT_LENGTH = 32
KEPT_PAIRS = 250_000
_PACKED = [struct.Struct(f"<{k}I") for k in range(17)]


def _byte_letters() -> dict[str, int]:
    """The letters that stand for bytes in the vocabulary file: printable Latin-1 for itself, the rest from U+0100 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(rest)}


def refuse_other_rules(spec: dict) -> None:
    """Raise for a file whose rules are not the ones implemented here: byte-level words, plain merges, bare specials."""
    model, before = spec["model"], spec.get("pre_tokenizer") or {}
    wrong = [
        ("model", model.get("type", "BPE") != "BPE"),
        ("normalizer", spec.get("normalizer") is not None),
        ("pre_tokenizer", before.get("type") != "ByteLevel" or before.get("add_prefix_space", True) or not before.get("use_regex", True)),
        ("decoder", (spec.get("decoder") or {}).get("type") != "ByteLevel"),
        ("merges", any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges"))),
        ("added_tokens", any(t.get(k) for t in spec["added_tokens"] for k in ("single_word", "lstrip", "rstrip"))),
    ]
    if found := [name for name, bad in wrong if bad]:
        raise ValueError(f"this vocabulary file has rules that the encoder does not know: {', '.join(found)}")


class Bpe:
    """Encoder and decoder for one vocabulary file; ids below are merge ranks, least first."""

    def __init__(self, file: bytes):
        spec = json.loads(file)
        refuse_other_rules(spec)
        model, letter = spec["model"], _byte_letters()
        as_bytes = lambda s: bytes(letter[c] for c in s)
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        size = max([*model["vocab"].values(), *self.special.values()]) + 1
        self.token: list[bytes] = [b""] * size
        for s, i in model["vocab"].items():
            if s not in self.special:
                self.token[i] = as_bytes(s)
        for s, i in self.special.items():
            self.token[i] = s.encode()
        ids = {self.token[i]: i for s, i in model["vocab"].items() if s not in self.special}
        self.parts: dict[int, tuple[int, int]] = {}
        self.joined: dict[tuple[int, int], int] = {}
        self.rank: dict[int, int] = {i: -1 for i in ids.values()}
        for r, pair in enumerate(model["merges"]):
            left, right = (ids[as_bytes(x)] for x in (pair if isinstance(pair, list) else pair.split(" ")))
            whole = ids[self.token[left] + self.token[right]]
            self.parts.setdefault(whole, (left, right))
            self.joined[left, right] = whole
            self.rank[whole] = min(r, self.rank[whole]) if self.rank[whole] >= 0 else r
        self.ids = ids
        self.finder = ahocorasick.Automaton()
        for t, i in ids.items():
            self.finder.add_word(t.decode("latin-1"), (len(t), i))
        self.finder.make_automaton()
        self.shorter: dict[int, int] = {}
        self.fits: dict[int, bool] = {}
        self.words: dict[str, bytes] = {}
        self.split = regex.compile(WORD_PATTERN).findall
        self.cut_special = regex.compile("(" + "|".join(regex.escape(s) for s in sorted(self.special, key=len, reverse=True)) + ")").split if self.special else None
        lengths = np.array([len(t) for t in self.token], np.int64)
        self.offset = np.concatenate(([0], np.cumsum(lengths)))
        self.store = np.frombuffer(b"".join(self.token), np.uint8)

    def _prefix(self, token: int) -> int:
        """The longest token that is a proper prefix of ``token``, -1 for a single byte."""
        if token not in self.shorter:
            t = self.token[token]
            self.shorter[token] = next((self.ids[t[:k]] for k in range(len(t) - 1, 0, -1) if t[:k] in self.ids), -1)
        return self.shorter[token]

    def compatible(self, left: int, right: int) -> bool:
        """Would the merges leave the border between these two tokens alone?"""
        pair = left << 32 | right
        known = self.fits.get(pair)
        if known is None:
            if len(self.fits) >= KEPT_PAIRS:
                self.fits.clear()
            known = self.fits[pair] = self._compatible(left, right)
        return known

    def _compatible(self, left: int, right: int) -> bool:
        """Undo merges on both sides, latest first; fail if the border pair has a merge that comes before the undone one.

        Of two merges of one rank the left one comes first, so an undone merge on the right bounds from its own rank
        inclusively and one on the left exclusively.
        """
        rank, end = self.rank, 1 << 60
        while True:
            across = self.joined.get((left, right))
            if across is not None and rank[across] < end:
                return False
            rl, rr = rank[left], rank[right]
            if rl < 0 and rr < 0:
                return True
            if rl > rr:
                end, left = rl, self.parts[left][1]
            else:
                end, right = rr + 1, self.parts[right][0]

    def encode_word(self, word: bytes) -> list[int]:
        whole = self.ids.get(word)
        if whole is not None:
            return [whole]
        n, token_at, shorter, compatible = len(word), self.token, self.shorter, self.compatible
        longest, size = [-1] * n, [0] * n
        for end, (length, token) in self.finder.iter(word.decode("latin-1")):
            at = end - length + 1
            if length > size[at]:
                size[at], longest[at] = length, token
        dead = bytearray(n + 1)
        out: list[int] = []
        at, last, token = 0, -1, longest[0]
        while True:
            while token >= 0:
                after = at + len(token_at[token])
                if not dead[after] and (last < 0 or compatible(last, token)):
                    break
                token = shorter[token] if token in shorter else self._prefix(token)
            if token >= 0:
                out.append(token)
                if after == n:
                    return out
                at, last, token = after, token, longest[after]
            else:
                dead[at] = 1
                token = out.pop()
                at -= len(token_at[token])
                last = out[-1] if out else -1
                token = self._prefix(token)

    def encode(self, text: str) -> bytes:
        """Ids of the whole text as little-endian unsigned 32-bit numbers."""
        if any(s in text for s in self.special):
            return b"".join(self.special[p].to_bytes(4, "little") if p in self.special else self._plain(p) for p in self.cut_special(text) if p)
        return self._plain(text)

    def _plain(self, text: str) -> bytes:
        known, out = self.words, []
        for w in self.split(text):
            ids = known.get(w)
            if ids is None:
                code = self.encode_word(w.encode())
                ids = _PACKED[len(code)].pack(*code) if len(code) < len(_PACKED) else np.array(code, "<u4").tobytes()
                if len(known) < KEPT_WORDS and len(w) <= KEPT_LENGTH:
                    known[w] = ids
            out.append(ids)
        return b"".join(out)

    def decode(self, ids: bytes) -> str:
        return self.decode_bytes(ids).decode("utf-8", "replace")

    def decode_bytes(self, ids: bytes) -> bytes:
        i = np.frombuffer(ids, "<u4").astype(np.int64)
        start, size = self.offset[i], self.offset[i + 1] - self.offset[i]
        ends = np.cumsum(size)
        if not len(ends):
            return b""
        return self.store[np.arange(int(ends[-1])) + np.repeat(start - (ends - size), size)].tobytes()


def load(name: str) -> Bpe:
    with open(name, "rb") as f:
        return Bpe(f.read())


def _coded(spec: bytes, key: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = held(key, lambda: Bpe(spec))
        for whole in batches:
            for at in range(0, whole.num_rows, 200):
                batch = whole.slice(at, 200)
                n, sha, back, ids = [], [], [], []
                for text in batch.column(1).to_pylist():
                    code = bpe.encode(text or "")
                    ids.append(code)
                    n.append(len(code) // 4)
                    sha.append(hashlib.sha256(code).hexdigest())
                    back.append(hashlib.sha256(bpe.decode(code).encode()).hexdigest())
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(sha, pa.string()), pa.array(back, pa.string()), pa.array(ids, pa.binary())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "ids"])
            give_back()

    return run


def encode_documents(docs: DataFrame, tokenizer: str) -> DataFrame:
    """Tokens of every whole text of ``docs(doc_id long, text string, ...)`` under the vocabulary file ``tokenizer``.

    Returns ``doc_id, n_tokens, ids_sha256, decoded_sha256, ids`` (ids: little-endian unsigned 32-bit), a row for each
    input row. A null text is the empty text with no tokens; null or repeated doc_ids pass through; other columns are
    ignored; an empty table gives an empty result. The file is read on the driver and travels with the task, so
    executors need no path to it.
    """
    with open(tokenizer, "rb") as f:
        spec = f.read()
    key = hashlib.sha256(spec).hexdigest()
    out = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, ids binary"
    return small_batches(docs).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_coded(spec, key), out)
