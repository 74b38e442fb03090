"""Byte-level BPE by prefix-sharing trie traversal.

The encoding of a prefix is fixed by its last token: dropping that token leaves the encoding
of a shorter prefix. So a word's encoding is a chain of last tokens, and words that share a
prefix share the chain up to it. New words are walked in sorted order, which is the
depth-first order of their trie, and each trie edge is computed once.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from gridchain.llm.charclasses import outside, probe
from gridchain.llm.shared import CACHES, small_batches, text_slices

#: Words and token pairs that one worker remembers before it starts anew.
MEMORY, PAIRS = 600_000, 1_200_000
#: Bytes at the end of a token by which the longest one is looked up.
TAIL = 4
#: Bytes of text whose new words are encoded at once.
ENCODED_BYTES = 4 << 20


def fast_cutter(pieces):
    """The same cut for texts below U+3000, with plain character classes."""
    letters, numbers, spaces = probe(pieces)
    return re.compile(f" ?[{letters}]+|'(?:[stmd]|re|ve|ll)| ?[{numbers}]+| ?[^{spaces}{letters}{numbers}]+|[{spaces}]+(?![^{spaces}])|[{spaces}]+").findall


_beyond = outside([])


def _byte_letters() -> dict[str, int]:
    """The letters that stand for bytes in the vocabulary file: printable ones for themselves, others from U+0100 on."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(0x100 + k): b for k, b in enumerate(rest)}


class TrieBpe:
    """Encoder and decoder for a byte-level BPE file of the tokenizers library."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        letters = _byte_letters()
        to_bytes = lambda token: bytes(letters[c] for c in token)
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        names = {t: i for t, i in spec["model"]["vocab"].items() if t not in self.special}
        self.ids = {to_bytes(t): i for t, i in names.items()}
        self.bytes = {i: b for b, i in self.ids.items()} | {i: t.encode() for t, i in self.special.items()}
        self.merged: dict[tuple[int, int], int] = {}
        made: dict[int, tuple[int, int, int]] = {}
        for rank, pair in enumerate(spec["model"]["merges"]):
            left, right = pair if isinstance(pair, list) else pair.split(" ")
            key = names[left], names[right]
            self.merged.setdefault(key, rank)
            made.setdefault(names[left + right], (rank, *key))
        # the longest token by its last bytes; other tokens are shorter than TAIL
        self.reach: dict[bytes, int] = {}
        for token in self.ids:
            if len(token) >= TAIL:
                self.reach[token[-TAIL:]] = max(self.reach.get(token[-TAIL:], 0), len(token))
        self.spelled = {i: str(i) for i in self.bytes}
        self._left = {t: self._spine(t, made, 1) for t in names.values()}
        self._right = {t: self._spine(t, made, 2) for t in names.values()}
        # a token that its own bytes don't merge to never ends an encoding
        self.whole = {b: i for b, i in self.ids.items() if len(b) == 1 or i in made}
        self._fits: dict[tuple[int, int], bool] = {}
        self.pre_tokenize = Tokenizer.from_file(path).pre_tokenizer.pre_tokenize_str
        self.cut_fast = fast_cutter(lambda text: [span for _, span in self.pre_tokenize(text)])
        self.at_special = re.compile("|".join(map(re.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None
        self.known: dict[str, tuple[str, int, bytes, tuple[int, ...]]] = {}

    @staticmethod
    def _spine(token: int, made: dict, side: int) -> list[tuple[int, float]]:
        """Tokens at one edge while `token` is built, with the rank at which each is merged away."""
        out, gone = [(token, float("inf"))], None
        while token in made:
            gone, token = made[token][0], made[token][side]
            out.append((token, gone))
        return out

    def fits(self, a: int, b: int) -> bool:
        """Whether a, b stay two tokens when their bytes are merged together."""
        key = a, b
        if (known := self._fits.get(key)) is None:
            known = True
            for x, x_gone in self._right[a]:
                for y, y_gone in self._left[b]:
                    rank = self.merged.get((x, y))
                    # of equal merges the leftmost goes first
                    if rank is not None and rank < x_gone and rank <= y_gone:
                        known = False
            if len(self._fits) >= PAIRS:
                self._fits.clear()
            self._fits[key] = known
        return known

    def encode_words(self, words: list[bytes]) -> Iterator[tuple[bytes, tuple[int, ...]]]:
        """(word, ids) of distinct words; shared prefixes are encoded once, and only those that some encoding may end with."""
        states: list[tuple[int, int] | None] = []  # last token and its length for each depth, None until it is asked for
        before = b""
        find, fits, seen, reach, short = self.whole.get, self.fits, self._fits.get, self.reach.get, TAIL - 1
        for word in sorted(words):
            shared, most = 0, min(len(before), len(word))
            while shared < most and before[shared] == word[shared]:
                shared += 1
            states[shared:] = [None] * (len(word) - shared)
            before, end = word, len(word)
            first, waiting = end - reach(word[-TAIL:], short), [(0, 0)]
            while end and (states[end - 1] is None or len(waiting) > 1):
                for start in range(first if first > 0 else 0, end):
                    token = find(word[start:end])
                    if token is None:
                        continue
                    if start:
                        state = states[start - 1]
                        if state is None:
                            waiting.append((end, start))
                            end, first = start, start - reach(word[start - TAIL : start], short) if start > TAIL else 0
                            break
                        fit = seen((state[0], token))
                        if not (fits(state[0], token) if fit is None else fit):
                            continue
                    states[end - 1] = token, end - start
                    end, first = waiting.pop()
                    break
                else:
                    raise ValueError(f"no token ends {word[:end]!r}")
            end, chain = len(word), []
            while end:
                token, size = states[end - 1]
                chain.append(token)
                end -= size
            yield word, tuple(chain[::-1])

    def learn(self, words: set[str]) -> None:
        """Remember the encodings of new words: ids as text, count, decoded bytes, ids."""
        if len(self.known) > MEMORY:
            self.known.clear()
        new = {w.encode(): w for w in words if w not in self.known}
        names, raws = self.spelled, self.bytes
        for raw, chain in self.encode_words(list(new)):
            self.known[new[raw]] = ",".join([names[t] for t in chain]), len(chain), b"".join([raws[t] for t in chain]), chain
        if self.special:
            for name, token in self.special.items():
                self.known[name] = str(token), 1, name.encode(), (token,)

    def cut(self, text: str) -> list[str]:
        return [text[a:b] for _, (a, b) in self.pre_tokenize(text)] if _beyond(text) else self.cut_fast(text)

    def words(self, text: str) -> list[str]:
        if self.at_special is None or not self.at_special.search(text):
            return self.cut(text)
        out, start = [], 0
        for m in self.at_special.finditer(text):
            out += self.cut(text[start : m.start()])
            out.append(m[0])
            start = m.end()
        return out + self.cut(text[start:])

    def encode(self, texts: list[str]) -> list[list[tuple]]:
        """The remembered parts of each text, in order."""
        cut = [self.words(t) for t in texts]
        self.learn(set().union(*cut))
        known = self.known
        return [[known[w] for w in words] for words in cut]

    def decode(self, ids) -> str:
        return b"".join([self.bytes[i] for i in ids]).decode("utf-8", "replace")


_loaded: dict[str, TrieBpe] = {}
CACHES.append(lambda: [kept.clear() for x in _loaded.values() for kept in (x.known, x._fits)])


def load(path: str) -> TrieBpe:
    """One encoder for each file and Python worker."""
    if path not in _loaded:
        _loaded[path] = TrieBpe(path)
    return _loaded[path]


#: Columns that encode_decode can return, in this order.
OUTPUTS = {"n_tokens": "long", "ids": "array<int>", "decoded": "string", "ids_sha256": "string", "decoded_sha256": "string"}


def encode_decode(docs: DataFrame, path: str, outputs: tuple[str, ...] = ("n_tokens", "ids")) -> DataFrame:
    """doc_id and the chosen OUTPUTS of each text: token ids, and the text decoded from them.

    Null texts count as empty. Repeated rows and null doc_ids keep their rows; other columns
    are ignored. Strings of special tokens in a text become those tokens.
    """
    sha = lambda b: hashlib.sha256(b).hexdigest()
    make = {
        "n_tokens": lambda parts: sum([p[1] for p in parts]),
        "ids": lambda parts: [i for p in parts for i in p[3]],
        "decoded": lambda parts: b"".join([p[2] for p in parts]).decode("utf-8", "replace"),
        "ids_sha256": lambda parts: sha(",".join([p[0] for p in parts]).encode()),
        "decoded_sha256": lambda parts: sha(b"".join([p[2] for p in parts]).decode("utf-8", "replace").encode()),
    }
    kinds = {"n_tokens": pa.int64(), "ids": pa.list_(pa.int32())}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for batch in batches:
            for part in text_slices(batch, "text", ENCODED_BYTES):
                rows = bpe.encode([t or "" for t in part.column("text").to_pylist()])
                columns = [pa.array([make[name](parts) for parts in rows], kinds.get(name, pa.string())) for name in outputs]
                yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), *columns], ["doc_id", *outputs])

    schema = ", ".join(["doc_id long", *[f"{name} {OUTPUTS[name]}" for name in outputs]])
    small_batches(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, schema)


def decode_ids(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id, text decoded from the ids column; null ids give an empty text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for batch in batches:
            texts = [bpe.decode(ids or []) for ids in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")
