"""Hierarchical residual packing of tokenized documents into sequences of a fixed capacity.

Every partition packs its own pieces best-fit; nearly full bins are final. The underfull
bins become the items of the next round on fewer partitions, until one partition holds the
few that are left. A bin carries its pieces, at most one for each token of its capacity, so
no join puts them together again.
"""

from __future__ import annotations

import re
import unicodedata
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridchain.llm.charclasses import TOP, outside, probe
from gridchain.llm.shared import CACHES, binary_array, stage, text_slices, tidy

CAPACITY = 4096
#: Share of the capacity from which a bin is final.
NEARLY_FULL = 0.985
#: Partitions that one task of the next round takes.
FAN_IN = 8
MEMORY = 400_000
#: Bytes of text whose new words are encoded at once.
ENCODED_BYTES = 4 << 20
PIECE = np.dtype([("doc_id", "<i8"), ("known", "<i1"), ("piece", "<i4"), ("start", "<i8"), ("length", "<i4"), ("crc", "<u4")])


def _normal(text: str) -> str:
    """What the tokenizer's normaliser does, but for white space, which no token holds."""
    return text.lower() if text.isascii() else unicodedata.normalize("NFC", text).replace("Σ", "σ").lower()


class WordIds:
    """Token ids of texts as little-endian bytes; each distinct word is encoded once by the library."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        added = {t.content: i for i, t in self.tokenizer.get_added_tokens_decoder().items()}
        self.special = {name: np.array([i], "<u4").tobytes() for name, i in added.items()}
        self.at_special = re.compile("|".join(map(re.escape, added))) if added else None
        letters, numbers, spaces = probe(lambda text: [span for _, span in self.tokenizer.pre_tokenizer.pre_tokenize_str(text)])
        self.pieces = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{letters}]+|[{numbers}]|[^{spaces}{letters}{numbers}]+").findall
        same = self.tokenizer.normalizer.normalize_str
        gap = re.compile(f"[{spaces}]+")
        # among marks of the highest and the lowest class, a mark shows whether its own class is known
        tries = (lambda c: c, lambda c: f"a\u0345{c}\u0334")
        odd = [c for c in range(TOP) if any(gap.sub(" ", _normal(t(chr(c)))) != same(t(chr(c))) for t in tries)]
        self.beyond, self.plain_ascii = outside(odd), not any(c < 128 for c in odd)
        self.risen = outside([])
        self.model = self.tokenizer.model
        self.spelled = self._spelling()
        self.known: dict[str, bytes] = {}

    def _spelling(self) -> dict[int, str] | None:
        """The characters that stand for bytes in the model's words; None if some probe's ids differ from the library's whole way."""
        from tokenizers.pre_tokenizers import ByteLevel

        level, out = ByteLevel(add_prefix_space=False, use_regex=False), {}
        for code in [*range(0x800), *range(0x800, TOP, 0x40)]:
            out.update(zip(chr(code).encode(), level.pre_tokenize_str(chr(code))[0][0]))
        words = [*(chr(c) * n for c in range(0x21, 0x800) for n in (1, 3)), "'ll", "understanding", "#$%&", "straße", "\u2014\u20ac"]
        probes = [x for x in words if self.cut(x) == [x]]
        return out if self._modelled(probes, out) == self._library(probes) else None

    def cut(self, text: str) -> list[str] | None:
        """Words of a text; None if only the library can tell."""
        if self.plain_ascii and text.isascii() and (self.at_special is None or "<|" not in text):
            return self.pieces(text.lower())
        if self.beyond(text):
            return None
        if self.at_special is None or "<|" not in text:
            plain = _normal(text)
            return None if self.risen(plain) else self.pieces(plain)
        if self.risen(_normal(text)):
            return None
        out, start = [], 0
        for m in self.at_special.finditer(text):
            out += [*self.pieces(_normal(text[start : m.start()])), m[0]]
            start = m.end()
        return out + self.pieces(_normal(text[start:]))

    def _library(self, texts: list[str]) -> list[bytes]:
        return [np.array(found.ids, "<u4").tobytes() for found in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _modelled(self, words: list[str], spelled: dict[int, str]) -> list[bytes]:
        """Ids of single words from the library's model, past its normaliser and its cutting, which they have behind them."""
        tokens, flat, cuts = self.model.tokenize, [], [0]
        for word in words:
            flat += [t.id for t in tokens(word if word.isascii() and word.isalnum() else word.encode().decode("latin-1").translate(spelled))]
            cuts.append(4 * len(flat))
        raw = np.array(flat, "<u4").tobytes()
        return [raw[a:b] for a, b in zip(cuts, cuts[1:])]

    def encode(self, texts: list[str]) -> list[bytes]:
        cut = [self.cut(t) for t in texts]
        if len(self.known) > MEMORY:
            self.known.clear()
        self.known.update(self.special)
        new = list(set().union(*[words for words in cut if words]).difference(self.known))
        self.known.update(zip(new, self._modelled(new, self.spelled) if self.spelled else self._library(new)))
        ids = self.known.__getitem__
        return [self._library([t])[0] if words is None else b"".join(map(ids, words)) for t, words in zip(texts, cut)]


_loaded: dict[str, WordIds] = {}
CACHES.append(lambda: [x.known.clear() for x in _loaded.values()])


def load(path: str) -> WordIds:
    if path not in _loaded:
        _loaded[path] = WordIds(path)
    return _loaded[path]


def cut_pieces(doc_ids: list, texts: list[str], ids: WordIds, end: int, capacity: int) -> np.ndarray:
    """Pieces of at most `capacity` tokens; every document ends with the id `end`."""
    last, out = np.array([end], "<u4").tobytes(), []
    for doc_id, raw in zip(doc_ids, ids.encode(texts)):
        raw += last
        for k, at in enumerate(range(0, len(raw), 4 * capacity)):
            part = raw[at : at + 4 * capacity]
            out.append((doc_id or 0, doc_id is not None, k, at // 4, len(part) // 4, zlib.crc32(part)))
    return np.array(out, PIECE)


def best_fit(sizes: np.ndarray, capacity: int) -> list[list[int]]:
    """Items in bins: the largest item first, each into the fullest bin that still takes it."""
    open_bins: list[list[int]] = [[] for _ in range(capacity + 1)]  # by free space
    free = 0  # bit s is set when some bin has s tokens free
    bins: list[list[int]] = []
    for item in np.argsort(-sizes, kind="stable").tolist():
        size = int(sizes[item])
        fit = free >> size
        if fit:
            space = size + (fit & -fit).bit_length() - 1
            at = open_bins[space].pop()
            if not open_bins[space]:
                free &= ~(1 << space)
            bins[at].append(item)
        else:
            space, at = capacity, len(bins)
            bins.append([item])
        left = space - size
        if left:
            open_bins[left].append(at)
            free |= 1 << left
    return bins


def _bins(sizes: np.ndarray, members: list[np.ndarray], capacity: int, nearly: float, last: bool) -> Iterator[pa.RecordBatch]:
    groups = best_fit(sizes, capacity)
    for start in range(0, len(groups), 4096):
        some = groups[start : start + 4096]
        fill = [int(sizes[g].sum()) for g in some]
        blobs = [np.concatenate([members[i] for i in g]).tobytes() for g in some]
        yield pa.RecordBatch.from_arrays([pa.array([last or f >= nearly * capacity for f in fill]), pa.array(fill, pa.int32()), binary_array(blobs)], ["final", "fill", "pieces"])


def _first_round(path: str, end: int, capacity: int, nearly: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, held = load(path), [np.zeros(0, PIECE)]
        for batch in batches:
            for part in text_slices(batch, "text", ENCODED_BYTES):
                held.append(cut_pieces(part.column("doc_id").to_pylist(), [t or "" for t in part.column("text").to_pylist()], ids, end, capacity))
        pieces = np.concatenate(held)
        yield from _bins(pieces["length"].astype(np.int64), [pieces[i : i + 1] for i in range(len(pieces))], capacity, nearly, False)

    return tidy(run)


def _next_round(capacity: int, nearly: float, last: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fill, members = [], []
        for batch in batches:
            fill += batch.column("fill").to_pylist()
            members += [np.frombuffer(b, PIECE) for b in batch.column("pieces").to_pylist()]
        yield from _bins(np.array(fill, np.int64), members, capacity, nearly, last)

    return tidy(run)


@tidy
def _unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        blobs = batch.column("pieces").to_pylist()
        sequence = np.asarray(batch.column("sequence_id"))
        for start in range(0, len(blobs), 2048):
            rows = [np.frombuffer(b, PIECE) for b in blobs[start : start + 2048]]
            every = np.concatenate(rows)
            owner = np.repeat(sequence[start : start + 2048], [len(r) for r in rows])
            offset = np.concatenate([np.cumsum(r["length"], dtype=np.int64) - r["length"] for r in rows])
            ids = pa.array(every["doc_id"].astype(np.int64), mask=every["known"] == 0)
            yield pa.RecordBatch.from_arrays([ids, pa.array(every["piece"].astype(np.int32)), pa.array(every["start"].astype(np.int64)), pa.array(every["length"].astype(np.int64)), pa.array(every["crc"].astype(np.int64)), pa.array(owner), pa.array(offset)], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])


BIN = "final boolean, fill int, pieces binary"
PLACED = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"


def pack_documents(docs: DataFrame, path: str, end: int = 1, capacity: int = CAPACITY, nearly: float = NEARLY_FULL, fan_in: int = FAN_IN) -> DataFrame:
    """Pieces of all documents with their place in a sequence of at most `capacity` tokens.

    Returns doc_id, piece, start, length, ids_crc32, sequence_id, offset. Null and empty texts
    are documents of one token, `end`. Repeated rows and null doc_ids are packed like others;
    other columns are ignored. An empty table gives no rows.
    """
    first = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_first_round(path, end, capacity, nearly), BIN)
    level = stage(first, "bins")
    done = level.filter("final")
    parts = max(1, level.rdd.getNumPartitions())
    while True:
        parts = -(-parts // fan_in)
        level = stage(level.filter("not final").select("fill", "pieces").repartition(parts).mapInArrow(_next_round(capacity, nearly, parts == 1), BIN), "bins")
        done = done.union(level.filter("final"))
        if parts == 1:
            break
    numbered = done.select(F.monotonically_increasing_id().alias("sequence_id"), "pieces")
    return numbered.mapInArrow(_unpacked, PLACED)
