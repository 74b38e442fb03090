"""Toxicity scores: boosted trees over lexicon, proximity, capitals, punctuation and obfuscation features."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridchain.llm.learning import BoostedTrees, IsotonicSteps, crc_of_id, labelled_sample
from gridchain.llm.shared import binary_array, forget, mix64, release, stage, text_slices, tidy
from gridchain.llm.words import LOWER, Words, distinct_sets

#: Insults that need no training.
SEED_WORDS = """idiot idiots stupid moron morons loser losers trash scum pathetic worthless disgusting clown clowns dumb fool
fools jerk ugly garbage vermin filth coward imbecile idiota estupido basura inutil asco payaso dumm blöd abschaum
widerlich versager müll stupide débile ordure minable dégoûtant nul""".split()
#: Second-person pronouns.
SECOND_PERSON = "you your yours yourself u ur du dich dir dein deine euch ihr tu te toi ton ta tes vous votre vos tú ti tus usted ustedes vosotros".split()
#: Signs often put in place of letters.
DISGUISES = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a", "$": "s", "!": "i"}

MAX_TRAIN = 20_000
MAX_LEXICON = 4096
NEAR = 5

_plain = LOWER.copy()
_plain[[ord(c) for c in DISGUISES]] = [ord(c) for c in DISGUISES.values()]
_letter = np.zeros(256, bool)
_letter[[*range(65, 91), *range(97, 123)]] = True
_letter[128:] = True
_disguise = np.zeros(256, bool)
_disguise[[ord(c) for c in DISGUISES]] = True
_punctuation = np.zeros(256, bool)
_punctuation[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = True


def _per_row(w: Words, flags: np.ndarray) -> np.ndarray:
    """Number of set bytes in each text."""
    total = np.concatenate([[0], np.cumsum(flags)])
    return total[w.cuts[1:]] - total[w.cuts[:-1]]


def _stripped(w: Words, table: np.ndarray) -> pa.Array:
    """Texts mapped by table, without punctuation (what a disguise leaves)."""
    mapped = table[w.raw]
    keep = ~_punctuation[mapped]
    total = np.concatenate([[0], np.cumsum(keep)])
    return pa.Array.from_buffers(pa.large_binary(), w.rows, [None, pa.py_buffer(total[w.cuts].astype(np.int64).tobytes()), pa.py_buffer(mapped[keep].tobytes())])


def _tokens(w: Words):
    """Hashes of each word, then of the first 4, 5 and 6 bytes of longer words (0 elsewhere)."""
    yield w.hashes()
    for size in (4, 5, 6):
        cut = mix64(w.hashes(size) + np.uint64(size))
        cut[w.ends - w.starts <= size] = 0
        yield cut


def word_hashes(words: list[str]) -> np.ndarray:
    return np.unique(Words(pa.array(words, pa.string())).hashes())


class KeySet:
    """Sorted hashes behind a table of their first 16 bits, which rejects most others."""

    def __init__(self, keys: np.ndarray):
        self.keys, self.table = keys, np.zeros(1 << 16, bool)
        self.table[keys >> np.uint64(48)] = True

    def find(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places of the hashes that are keys, and which keys they are."""
        maybe = np.flatnonzero(self.table[hashes >> np.uint64(48)])
        if not len(maybe):
            return maybe, maybe
        at = np.minimum(np.searchsorted(self.keys, hashes[maybe]), len(self.keys) - 1)
        right = self.keys[at] == hashes[maybe]
        return maybe[right], at[right]


@tidy
def _lexicon_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Documents by fold and label for each token of the training texts, summed within the batch."""
    for batch in batches:
        for part in text_slices(batch, "text"):
            labels, folds = np.asarray(part.column("label")), np.asarray(part.column("fold"))
            plain = Words(_stripped(Words(part.column("text")), LOWER))
            tokens = list(_tokens(plain))
            hashes, owners = np.concatenate(tokens), np.tile(plain.docs, len(tokens))
            hashes, cuts = distinct_sets(hashes[hashes != 0], owners[hashes != 0], plain.rows)
            mark = np.repeat(labels + 2 * folds, np.diff(cuts))
            order = np.lexsort((mark, hashes))
            hashes, mark = hashes[order], mark[order]
            new = np.ones(len(hashes), bool)
            new[1:] = (hashes[1:] != hashes[:-1]) | (mark[1:] != mark[:-1])
            first = np.flatnonzero(new)
            docs = np.diff(np.append(first, len(hashes)))
            yield pa.RecordBatch.from_arrays([pa.array(hashes[first].view(np.int64)), pa.array((mark[first] // 2).astype(np.int32)), pa.array((mark[first] % 2).astype(np.int32)), pa.array(docs)], ["token", "fold", "label", "docs"])


def learn_lexicons(train: DataFrame, folds: int, size: int = MAX_LEXICON) -> list[tuple[KeySet, np.ndarray]]:
    """Tokens far commoner in toxic texts, with their log odds; at most `size`, by likelihood ratio.

    The first lexicon is learned from all rows (text, label, fold); number k + 1 from those that are not of fold k.
    """
    totals = {(r["fold"], r["label"]): r["count"] for r in train.groupBy("fold", "label").count().collect()}  # two rows a fold
    cells = train.select("text", "label", "fold").mapInArrow(_lexicon_counts, "token long, fold int, label int, docs long")
    fits = [None, *range(folds)]
    sums = [F.sum(F.when((F.col("label") == y) & ((F.col("fold") != k) if k is not None else F.lit(True)), F.col("docs")).otherwise(0)).alias(f"{name}{at}") for at, k in enumerate(fits) for y, name in ((1, "bad"), (0, "good"))]
    counts = stage(cells.groupBy("token").agg(*sums).filter("bad0 >= 3"), "tokens")
    out = []
    for at, k in enumerate(fits):
        bad_docs, good_docs = (sum(n for (fold, label), n in totals.items() if label == y and fold != k) for y in (1, 0))
        if not bad_docs or not good_docs:
            out.append((KeySet(np.zeros(0, np.uint64)), np.zeros(0)))
            continue
        bad, good = F.col(f"bad{at}"), F.col(f"good{at}")
        odds = F.log((bad + 0.5) / (bad_docs + 1.0)) - F.log((good + 0.5) / (good_docs + 1.0))
        seen = bad + good
        expected = seen * (bad_docs / (bad_docs + good_docs))
        ratio = 2 * (bad * F.log(bad / expected) + F.when(good > 0, good * F.log(good / (seen - expected))).otherwise(0.0))
        rows = counts.filter(bad >= 3).select("token", odds.alias("odds"), ratio.alias("ratio")).filter("odds > 1.5 and ratio > 12").orderBy(F.desc("ratio"), "token").limit(size).collect()
        keys = np.array([r["token"] for r in rows], np.int64).view(np.uint64)
        order = np.argsort(keys)
        out.append((KeySet(keys[order]), np.array([r["odds"] for r in rows], float)[order]))
    return out


def _lexicon_hits(w: Words, table: np.ndarray, lexicon: tuple[KeySet, np.ndarray], second: bool) -> tuple[list[np.ndarray], np.ndarray]:
    """Columns about lexicon words and prefixes in texts mapped by table; words that hit, by text."""
    plain = Words(_stripped(w, table))
    rows, n, (keys, odds) = w.rows, len(plain.docs), lexicon
    words = np.maximum(plain.counts, 1)
    marks, columns = [], []
    total, peak = np.zeros(rows), np.zeros(rows)
    for k, hashes in enumerate(_tokens(plain)):
        if k == 0:
            seeds, _ = _SEED.find(hashes)
            seeded = np.bincount(plain.docs[seeds], minlength=rows)
            marks.append(seeds)
            columns += [seeded, seeded / words]
            spots = _SECOND.find(hashes)[0] if second else None
        place, which = keys.find(hashes)
        count = np.bincount(plain.docs[place], minlength=rows)
        columns += [np.minimum(count, 50), count / words]
        total += np.bincount(plain.docs[place], odds[which], rows)
        np.maximum.at(peak, plain.docs[place], odds[which])
        marks.append(place)
    marked = np.unique(np.concatenate(marks))
    columns += [total, total / words, peak]
    if second:
        near = np.zeros(n, bool)
        for step in range(-NEAR, NEAR + 1):
            to = spots + step
            inside = (to >= 0) & (to < n)
            same = plain.docs[spots[inside]] == plain.docs[to[inside]]
            near[to[inside][same]] = True
        columns += [np.bincount(plain.docs[spots], minlength=rows) / words, np.bincount(plain.docs[marked[near[marked]]], minlength=rows)]
    return columns, np.bincount(plain.docs[marked], minlength=rows)


def toxicity_features(column: pa.Array, lexicon: tuple[KeySet, np.ndarray]) -> np.ndarray:
    """Dense features of each text; empty texts get zeros."""
    w = Words(column)
    rows, words, raw = w.rows, np.maximum(w.counts, 1), w.raw
    out = [np.log1p(w.counts), np.log1p(np.diff(w.cuts))]
    columns, written = _lexicon_hits(w, LOWER, lexicon, second=True)
    out += columns
    # only texts with a sign beside a letter can hide a word behind signs
    letter, beside = _letter[raw], np.zeros(len(raw), bool)
    beside[1:] = letter[:-1]
    beside[:-1] |= letter[1:]
    disguised = _disguise[raw] & beside
    some = np.flatnonzero(_per_row(w, disguised) > 0)
    hidden = np.zeros(rows)
    if len(some):
        part = Words(column.take(pa.array(some)))
        hidden[some] = np.maximum(_lexicon_hits(part, _plain, lexicon, second=False)[1] - written[some], 0)
    size = np.maximum(np.diff(w.cuts), 1)
    capitals = (raw >= 65) & (raw <= 90)
    capital_sum = np.concatenate([[0], np.cumsum(capitals)])
    disguise_sum = np.concatenate([[0], np.cumsum(disguised)])
    length = w.ends - w.starts
    shouted = (capital_sum[w.ends] - capital_sum[w.starts] == length) & (length >= 3)
    mixed = disguise_sum[w.ends] > disguise_sum[w.starts]
    out += [_per_row(w, capitals) / size, np.bincount(w.docs[shouted], minlength=rows) / words, _per_row(w, _punctuation[raw]) / size, _per_row(w, raw == 33) / size, _per_row(w, raw == 63) / size, np.bincount(w.docs[mixed], minlength=rows) / words, hidden]
    return np.stack(out, axis=1).astype(float)


_SEED, _SECOND = KeySet(word_hashes(SEED_WORDS)), KeySet(word_hashes(SECOND_PERSON))


def _feature_rows(lexicons):
    """The features of each training row under each lexicon."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in text_slices(batch, "text"):
                x = np.stack([toxicity_features(part.column("text"), lexicon) for lexicon in lexicons], axis=1)
                yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), part.column("label").cast(pa.int32()), part.column("fold"), binary_array([r.tobytes() for r in x])], ["doc_id", "label", "fold", "x"])

    return tidy(run)


class ToxicityModel:
    """Scores texts; without a usable label every score is 0."""

    def __init__(self, lexicon, trees: BoostedTrees | None, steps: IsotonicSteps | None):
        self.lexicon, self.trees, self.steps = lexicon, trees, steps

    def score(self, column: pa.Array) -> np.ndarray:
        if self.trees is None:
            return np.zeros(len(column))
        raw = self.trees.raw(toxicity_features(column, self.lexicon))
        # the raw score keeps the order within a step of the calibration
        return np.clip(0.999 * self.steps(raw) + 0.001 / (1 + np.exp(-np.clip(raw, -40, 40))), 0.0, 1.0)


def fit_toxicity(docs: DataFrame, labels: DataFrame, max_train: int = MAX_TRAIN, folds: int = 3) -> ToxicityModel:
    """Fit on at most max_train labelled rows whose crc32(doc_id as text) mod 4 is not 2.

    The calibration is fitted on scores that each row got from a lexicon and trees learned without its fold.
    """
    train = labelled_sample(docs, labels, "toxic", crc_of_id() % 4 != 2, max_train)
    train = stage(train.withColumn("fold", F.pmod(F.xxhash64("doc_id", F.lit(17)), F.lit(folds)).cast("int")), "toxic-train")
    lexicons = learn_lexicons(train, folds)
    rows = train.mapInArrow(_feature_rows(lexicons), "doc_id long, label int, fold int, x binary").toPandas().sort_values(["doc_id", "label"], kind="stable")
    y, fold = rows["label"].to_numpy(float), rows["fold"].to_numpy()
    if not len(y) or y.min() == y.max():
        return ToxicityModel(lexicons[0], None, None)
    x = np.stack([np.frombuffer(b, float) for b in rows["x"]]).reshape(len(y), folds + 1, -1)
    raw, scored = np.zeros(len(y)), np.zeros(len(y), bool)
    for k in range(folds):
        inside = fold != k
        if inside.all() or not inside.any() or y[inside].min() == y[inside].max():
            continue
        raw[~inside] = BoostedTrees().fit(x[inside, k + 1], y[inside]).raw(x[~inside, k + 1])
        scored |= ~inside
    trees = BoostedTrees().fit(x[:, 0], y)
    # too few rows for folds: the trees' own scores are all there is
    steps = IsotonicSteps().fit(raw[scored], y[scored]) if scored.any() else IsotonicSteps().fit(trees.raw(x[:, 0]), y)
    del rows, x
    release(docs.sparkSession)
    return ToxicityModel(lexicons[0], trees, steps)


def _scored(model: ToxicityModel, threshold: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in text_slices(batch, "text"):
                score = model.score(part.column("text"))
                yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), part.column("held_out"), pa.array(score), pa.array((score >= threshold).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return tidy(run)


def toxicity_scores(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, max_train: int = MAX_TRAIN) -> DataFrame:
    """doc_id, held_out, score (0 to 1), predicted (score >= threshold) of each row of docs.

    Null or empty texts are scored as texts without words. A null doc_id keeps its row
    (held_out false). Repeated rows get equal scores; other columns are ignored.
    """
    model = fit_toxicity(docs, labels, max_train)
    rows = docs.select("doc_id", "text", F.coalesce(crc_of_id() % 4 == 2, F.lit(False)).alias("held_out"))
    return rows.mapInArrow(_scored(model, threshold), "doc_id long, held_out boolean, score double, predicted int")


def _accepted(model: ToxicityModel, threshold: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        for batch in batches:
            for part in text_slices(batch, "text"):
                yield part.filter(pa.array(model.score(part.column("text")) < threshold))

    return tidy(run)


def keep_harmless(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, max_train: int = MAX_TRAIN) -> DataFrame:
    """docs without the rows whose score reaches the threshold; all columns stay."""
    return docs.mapInArrow(_accepted(fit_toxicity(docs, labels, max_train), threshold), docs.schema)
