"""Byte-level BPE by a depth-first walk over the prefix trie of distinct words.

The BPE encoding of a prefix is fixed by its last token: it is the encoding of the prefix before that
token, then the token. So one last token per trie node holds every encoding; words that share a prefix
share its nodes. The last token of a node is the one vocabulary suffix that stays unmerged after its
left neighbour. Words in sorted order visit the trie depth first, and only the current path is kept.

Defined cases: null counts as empty (no ids, empty text back); special tokens in a text get their id; a text
of any length is encoded whole; repeated rows give repeated results; an empty table gives none; extra columns
are not read. A vocabulary file whose stages differ from byte-level BPE is refused.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator
from struct import pack

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from . import vec

#: fixed value: the pattern by which byte-level BPE vocabularies of this family cut a text into words
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
CACHE_WORDS = 450_000


def byte_names() -> dict[str, int]:
    """The printable characters that stand for bytes in vocabulary files of this kind."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    names = {chr(b): b for b in shown}
    names.update({chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in shown)})
    return names


def refuse_others(spec: dict) -> None:
    """Raise unless the file asks for byte-level BPE with the usual word pattern and nothing around it."""
    pre, model = spec.get("pre_tokenizer") or {}, spec["model"]
    plain = not spec.get("normalizer") and pre.get("type") == "ByteLevel" and pre.get("use_regex", True) and not pre.get("add_prefix_space")
    plain = plain and (spec.get("decoder") or {}).get("type") == "ByteLevel" and not any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges"))
    if not plain or any(t.get("lstrip") or t.get("rstrip") or t.get("single_word") for t in spec["added_tokens"]):
        raise ValueError("not a plain byte-level BPE vocabulary")


class Encoder:
    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        refuse_others(spec)
        names = byte_names()
        raw = lambda name: bytes(names[c] for c in name)
        self.ids = {raw(name): i for name, i in spec["model"]["vocab"].items() if all(c in names for c in name)}
        pairs = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        size = max([*self.ids.values(), *self.special.values()]) + 1
        self.bytes_of = [b""] * size
        for token, i in self.ids.items():
            self.bytes_of[i] = token
        for text, i in self.special.items():
            self.bytes_of[i] = text.encode()
        self.words = regex.compile(PATTERN)
        self.specials = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        self.made = [(-1, 0, 0)] * size  # rank of the merge that makes a token, and its two halves
        self.joins: dict[int, int] = {}  # left id << 20 | right id -> rank
        for rank, (a, b) in enumerate(map(lambda p: (raw(p[0]), raw(p[1])), pairs)):
            self.joins[self.ids[a] << 20 | self.ids[b]] = rank
            self.made[self.ids[a + b]] = (rank, self.ids[a], self.ids[b])
        self.whole = {t: i for t, i in self.ids.items() if len(t) == 1 or self._stays(*self.made[i][1:], before=self.made[i][0])}
        self.reach: dict[int, int] = {}  # longest token that ends with a byte
        for t in self.whole:
            self.reach[t[-1]] = max(self.reach.get(t[-1], 0), len(t))
        self.pairs: dict[int, bool] = {}
        self.encoded: dict[str, bytes] = {}

    def _stays(self, left: int, right: int, before: int = 1 << 40) -> bool:
        """Whether no merge of rank under ``before`` crosses the border of two tokens.

        Back in time from the finished tokens: a merge over the border would have come first if it ranks
        before the merges that used up the two pieces beside the border (leftmost first on equal rank)."""
        made, joins = self.made, self.joins
        left_used = right_used = before
        while True:
            rank = joins.get(left << 20 | right)
            if rank is not None and rank < left_used and (rank <= right_used if right_used != before else rank < before):
                return False
            a, b = made[left], made[right]
            if a[0] > b[0]:
                left_used, left = a[0], a[2]
            elif b[0] >= 0:
                right_used, right = b[0], b[1]
            else:
                return True

    def walk(self, words: list[bytes]) -> Iterator[list[int]]:
        """Ids of words in sorted order; the states of a shared prefix are computed once."""
        whole, reach, pairs, stays = self.whole.get, self.reach, self.pairs, self._stays
        if len(pairs) > 2_000_000:
            pairs.clear()
        last: list[int] = [-1]  # last token of the prefix of each length, and that token's length
        size: list[int] = [0]
        before = b""
        for word in words:
            shared, top = 0, min(len(before), len(word))
            while shared < top and before[shared] == word[shared]:
                shared += 1
            del last[shared + 1 :], size[shared + 1 :]
            for end in range(shared + 1, len(word) + 1):
                for start in range(max(0, end - reach[word[end - 1]]), end):
                    token = whole(word[start:end])
                    if token is None:
                        continue
                    if start:
                        key = last[start] << 20 | token
                        fits = pairs.get(key)
                        if fits is None:
                            fits = pairs[key] = stays(last[start], token)
                        if not fits:
                            continue
                    last.append(token)
                    size.append(end - start)
                    break
            out, end = [], len(word)
            while end:
                out.append(last[end])
                end -= size[end]
            out.reverse()
            yield out
            before = word

    def learn(self, words: set[str]) -> None:
        if len(self.encoded) > CACHE_WORDS:
            self.encoded.clear()
        fresh = sorted((w.encode(), w) for w in words if w not in self.encoded)
        for (_, word), ids in zip(fresh, self.walk([b for b, _ in fresh]), strict=True):
            self.encoded[word] = pack(f"<{len(ids)}I", *ids)

    def split(self, text: str) -> list[str | int]:
        """Words of a text; a special token is its id."""
        if self.specials is None or not any(s in text for s in self.special):
            return self.words.findall(text)
        out: list[str | int] = []
        for part in self.specials.split(text):
            out += [self.special[part]] if part in self.special else self.words.findall(part)
        return out

    def encode_batch(self, texts: list[str | None]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        cut = [self.split(t or "") for t in texts]
        self.learn({w for words in cut for w in set(words) if isinstance(w, str)})
        known = self.encoded
        return [
            b"".join(map(known.__getitem__, words)) if not any(type(w) is int for w in words) else b"".join(w.to_bytes(4, "little") if type(w) is int else known[w] for w in words)
            for words in cut
        ]

    def decode(self, ids: bytes) -> str:
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, "<u4").tolist())).decode("utf-8", "replace")


_ENCODERS: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """One per Python worker: its word cache serves all tasks that the worker runs."""
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]


def encode(docs: DataFrame, path: str) -> DataFrame:
    """doc_id and ids (little-endian unsigned 32-bit integers) of every row."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in vec.slices(batches, "text"):
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(encoder(path).encode_batch(batch.column("text").to_pylist()), pa.binary())], names=["doc_id", "ids"])

    return docs.select("doc_id", "text").mapInArrow(rows, f"doc_id {kind}, ids binary")


def decode(coded: DataFrame, path: str) -> DataFrame:
    """doc_id and text of rows made by :func:`encode`."""
    kind = coded.schema["doc_id"].dataType.simpleString()

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([encoder(path).decode(x) for x in batch.column("ids").to_pylist()], pa.string())], names=["doc_id", "text"])

    return coded.select("doc_id", "ids").mapInArrow(rows, f"doc_id {kind}, text string")


def round_trip(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_tokens, digest of the ids and of the text decoded from them, in one pass."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = encoder(path)
        for batch in vec.slices(batches, "text"):
            ids = bpe.encode_batch(batch.column("text").to_pylist())
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id"),
                    pa.array([len(x) // 4 for x in ids], pa.int64()),
                    pa.array([hashlib.sha256(x).hexdigest() for x in ids]),
                    pa.array([hashlib.sha256(bpe.decode(x).encode()).hexdigest() for x in ids]),
                ],
                names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    return docs.select("doc_id", "text").mapInArrow(rows, f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
