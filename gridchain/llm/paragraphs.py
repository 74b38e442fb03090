"""Removal of repeated paragraphs and passages: MinHash bands find candidates, exact Jaccard decides, components cluster.

A paragraph is a line of LEAST_WORDS words or more, or successive shorter lines joined until
they hold as many. One of more than LONGEST words is cut into pieces at anchors: word
boundaries that only the REACH words around them choose, sentence ends first. So a passage
is cut into the same pieces wherever in a line it lies, and its copies share pieces. What repeats
is removed as ranges of words; ranges that touch are one, and one of fewer than
LEAST_RUN words stays. Units with equal sets of word 5-grams are one node from the start,
so a passage in any number of documents is hashed, compared and clustered once.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridchain.llm.linkage import bucket_links
from gridchain.llm.shared import Packer, binary_array, bucket_count, forget, group_cuts, ids_of, mix64, release, stage, text_bytes, text_slices, tidy, unpack, unstage
from gridchain.llm.words import Words, distinct_sets, group_shingles, sliding

#: Shortest paragraph that is compared, in words; shorter lines are joined.
LEAST_WORDS = 20
#: Longest paragraph that is one unit, in words.
LONGEST = 50
#: Words on each side of a boundary that decide whether it is an anchor; a piece has more words than that.
REACH = 5
#: Shortest range that is removed, in words. A passage of 51 words holds one in 93 of 100 places, of 60 words in 97.
LEAST_RUN = 16
#: Most hash functions, and the recall at the threshold that bands are tuned for.
HASHES, RECALL = 16, 0.999
BUCKET_KEYS = 1 << 20
STOP = np.zeros(256, bool)
STOP[[ord(c) for c in ".!?"]] = True


def tune_bands(threshold: float, hashes: int = HASHES, recall: float = RECALL) -> tuple[int, int]:
    """(bands, rows): the longest bands whose chance to collide at the threshold reaches the recall, no more of them than that needs."""
    best = (hashes, 1)
    for rows in range(1, hashes + 1):
        for bands in range(1, hashes // rows + 1):
            if 1 - (1 - threshold**rows) ** bands >= recall:
                best = (bands, rows)
                break
    return best


def join_short(counts: np.ndarray, docs: np.ndarray, line: np.ndarray, least: int) -> np.ndarray:
    """Whether each line with words starts a paragraph.

    A paragraph of short lines ends once it holds `least` words. Its block's remaining lines,
    if they hold fewer, go to it too; a block (up to an empty line) with fewer words in all
    goes on in the next one.
    """
    starts = np.ones(len(counts), bool)
    places = np.flatnonzero(counts < least)
    at, previous, alone = -2, -1, True
    held, block = 0, False  # words since the last start; whether its block holds a full paragraph before it
    for i, n, doc, row in zip(places.tolist(), counts[places].tolist(), docs[places].tolist(), line[places].tolist()):
        alone = i != at + 1 or doc != of
        if alone or row > previous + 1:  # a run or a block ends
            if at >= 0 and held < least and block:
                starts[begin] = False
                held = least
            block = False
        if not alone and held < least:
            starts[i], held = False, held + n
        else:
            block = not alone and row == previous + 1
            begin, held = i, n
        at, of, previous = i, doc, row
    if at >= 0 and held < least and block:
        starts[begin] = False
    return starts


def anchors(w: Words, group: np.ndarray, reach: int = REACH) -> np.ndarray:
    """Whether each word's boundary has the least score of those up to `reach` words away in its group of words.

    The score depends on the two words at the boundary; sentence ends go before others. Of
    equal scores the first counts, so a word repeated on and on has no anchor.
    """
    n, hashes = len(w.starts), w.hashes()
    if not n:
        return np.zeros(0, bool)
    score, inside = np.zeros(n, np.uint64), np.ones(n, np.uint64)
    score[1:] = mix64(hashes[1:] ^ hashes[:-1] * np.uint64(0xA0761D6478BD642F))
    inside[1:] = ~STOP[w.raw[w.ends[:-1] - 1]]
    score = score >> np.uint64(1) | inside << np.uint64(63)
    place = np.arange(n) + (group + 1) * reach  # no window of one group reaches another
    padded = np.full(int(place[-1]) + reach + 1, np.uint64(0xFFFFFFFFFFFFFFFF))
    padded[place] = score
    around = sliding(np.minimum, padded, 2 * reach + 1)[place - reach]
    before = sliding(np.minimum, padded, reach)[place - reach]
    return (around == score) & (before > score)


def unit_starts(w: Words, least: int, longest: int = LONGEST, reach: int = REACH) -> np.ndarray:
    """Word numbers at which units start: paragraphs, and pieces of long ones."""
    breaks = np.concatenate([[0], np.cumsum(w.raw == 10)])
    line = breaks[w.starts] - breaks[w.cuts[:-1]][w.docs]
    new = np.ones(len(line), bool)
    new[1:] = (line[1:] != line[:-1]) | (w.docs[1:] != w.docs[:-1])
    first = np.flatnonzero(new)
    first = first[join_short(np.diff(np.append(first, len(line))), w.docs[first], line[first], least)]
    counts = np.diff(np.append(first, len(line)))
    group = np.repeat(np.arange(len(first)), counts)
    place = np.arange(len(line)) - first[group] if len(line) else group
    # a piece at either end of a paragraph has more than `reach` words too
    cut = anchors(w, group, reach) & (counts[group] > longest) & (place > reach) & (counts[group] - place > reach)
    cut[first] = True
    return np.flatnonzero(cut)


class Units:
    """Units of a text column, with the 5-gram set of each; `start` and `n` count words of the text."""

    def __init__(self, column: pa.Array, least: int, size: int = 5):
        w = Words(column, lower=True)
        first = unit_starts(w, least)
        bounds = np.append(first, len(w.starts)).astype(np.int64)
        counts = np.diff(bounds)
        chosen = counts > REACH
        hashes, owners = group_shingles(w.hashes(), bounds, size)
        slot, keep = np.cumsum(chosen) - 1, chosen[owners]
        self.tokens, self.cuts = distinct_sets(hashes[keep], slot[owners[keep]], int(chosen.sum()))
        first, self.n = first[chosen], counts[chosen]
        self.doc = w.docs[first]
        self.start = first - w.first_word[self.doc]
        sums = np.add.reduceat(mix64(self.tokens), self.cuts[:-1]) if len(first) else np.zeros(0, np.uint64)
        self.node = mix64(sums ^ mix64(np.diff(self.cuts).astype(np.uint64))).view(np.int64)


def _listed(least: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        for batch in batches:
            for part in text_slices(batch, "text"):
                u = Units(part.column("text"), least)
                at = pa.array(u.doc)
                yield pa.RecordBatch.from_arrays([part.column("doc_id").take(at), part.column("copy").take(at), pa.array(u.start.astype(np.int32)), pa.array(u.n.astype(np.int32)), pa.array(u.node)], ["doc_id", "copy", "word", "n", "node"])

    return tidy(run)


def signatures(tokens: np.ndarray, cuts: np.ndarray, hashes: int, seed: int = 1) -> np.ndarray:
    """MinHash values of each set (sets are not empty), one column for each hash function."""
    rng = np.random.default_rng(seed)
    factors = rng.integers(0, 1 << 63, hashes, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    shifts = rng.integers(0, 1 << 63, hashes, dtype=np.uint64)
    out = np.empty((len(cuts) - 1, hashes), np.uint64)
    for k in range(hashes):
        spread = tokens * factors[k] + shifts[k]
        spread ^= spread >> np.uint64(32)
        spread *= factors[k]
        out[:, k] = np.minimum.reduceat(spread, cuts[:-1]) if len(cuts) > 1 else 0
    return out


def _banded(least: int, bands: int, rows: int, buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        packer, seen = Packer(["keys", "nodes"], [np.uint32, np.int64]), set()
        for batch in batches:
            for part in text_slices(batch, "text"):
                u = Units(part.column("text"), least)
                fresh = np.zeros(len(u.node), bool)
                for i, node in enumerate(u.node.tolist()):
                    if node not in seen:  # copies within a task are hashed once
                        seen.add(node)
                        fresh[i] = True
                if len(seen) > 1 << 18:
                    seen.clear()
                sizes = np.diff(u.cuts)
                tokens = u.tokens[np.repeat(fresh, sizes)]
                cuts = np.concatenate([[0], np.cumsum(sizes[fresh])])
                nodes = u.node[fresh]
                if not len(nodes):
                    continue
                mins = signatures(tokens, cuts, bands * rows)
                for b in range(bands):
                    key = np.full(len(nodes), np.uint64(b + 1))
                    for k in range(b * rows, (b + 1) * rows):
                        key = mix64(key * np.uint64(0x9E3779B97F4A7C15) + mins[:, k])
                    # the bucket stands for the upper half of a key; false collisions are verified away
                    yield from packer.add((key >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32), key.astype(np.uint32), nodes)
        yield from packer.flush()

    return tidy(run)


@tidy
def _colliding(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Nodes of the keys that more than one node has, bucket by bucket."""
    held: dict[int, list[pa.RecordBatch]] = {}
    for batch in batches:
        for at, bucket in enumerate(batch.column("bucket").to_pylist()):
            held.setdefault(bucket, []).append(batch.slice(at, 1))
    for bucket in sorted(held):
        keys, nodes = unpack(held.pop(bucket), ["keys", "nodes"], [np.uint32, np.int64])
        order = np.lexsort((nodes, keys))
        keys, nodes = keys[order], nodes[order]
        keep = np.ones(len(keys), bool)
        keep[1:] = (keys[1:] != keys[:-1]) | (nodes[1:] != nodes[:-1])
        keys, nodes = keys[keep], nodes[keep]
        counts = np.diff(group_cuts(keys))
        several = np.repeat(counts > 1, counts)
        keys, nodes = keys[several].astype(np.int64) | np.int64(bucket) << np.int64(32), nodes[several]
        for a in range(0, len(keys), 1 << 16):
            yield pa.RecordBatch.from_arrays([pa.array(keys[a : a + (1 << 16)]), pa.array(nodes[a : a + (1 << 16)])], ["bucket_key", "node"])


def _chosen_sets(least: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        for batch in batches:
            for part in text_slices(batch, "text"):
                u = Units(part.column("text"), least)
                place = {(d, n): i for i, (d, n) in enumerate(zip(u.doc.tolist(), u.node.tolist()))}
                rows = [place[d, n] for d, wanted in enumerate(part.column("wanted").to_pylist()) for n in wanted if (d, n) in place]
                yield pa.RecordBatch.from_arrays([pa.array(u.node[rows]), pa.array(np.diff(u.cuts)[rows]), binary_array([u.tokens[u.cuts[i] : u.cuts[i + 1]].tobytes() for i in rows])], ["node", "n", "tokens"])

    return tidy(run)


def _similar(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes = ids_of(batch.column("a_n")) + ids_of(batch.column("b_n"))
            left, right = text_bytes(batch.column("a_tokens")), text_bytes(batch.column("b_tokens"))
            x, y = np.frombuffer(left[0].tobytes(), np.uint64), np.frombuffer(right[0].tobytes(), np.uint64)
            keep = np.zeros(batch.num_rows, bool)
            for i in range(batch.num_rows):
                a, b = x[left[1][i] // 8 : left[1][i + 1] // 8], y[right[1][i] // 8 : right[1][i + 1] // 8]
                common = len(np.intersect1d(a, b, assume_unique=True))
                keep[i] = 100 * common >= percent * (sizes[i] - common)
            yield pa.RecordBatch.from_arrays([batch.column("a").filter(pa.array(keep)), batch.column("b").filter(pa.array(keep))], ["a", "b"])

    return tidy(run)


def _known(docs: DataFrame) -> DataFrame:
    """Rows that take part; copy tells rows that repeat a doc_id with another text."""
    known = docs.filter("doc_id is not null and text is not null")
    return known.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("copy"), "text")


def repeated_units(docs: DataFrame, percent: int = 80, least: int = LEAST_WORDS, hashes: int = HASHES, recall: float = RECALL) -> DataFrame:
    """doc_id, copy, word, n, repeated_id, repeated_word of every paragraph and piece that repeats an earlier one.

    A unit has the n words from number `word` (from 0) on. Earlier means a smaller
    (doc_id, copy, word) in the same component of similar units; the first of a component is
    at repeated_id, repeated_word. A unit that overlaps that first one does not repeat it. Rows with a null doc_id or text take no part. Rows
    that repeat a doc_id and a text are one document; if their texts differ, copy, a hash of
    the text, tells them apart and orders them.
    """
    spark, docs = docs.sparkSession, _known(docs)
    listed = stage(docs.mapInArrow(_listed(least), "doc_id long, copy long, word int, n int, node long"), "units")
    bands, rows = tune_bands(percent / 100, hashes, recall)
    buckets = bucket_count(spark, listed.count() * bands, BUCKET_KEYS)
    keys = docs.mapInArrow(_banded(least, bands, rows, buckets), "bucket int, keys binary, nodes binary").repartition(buckets, "bucket")
    members = stage(keys.mapInArrow(_colliding, "bucket_key long, node long"), "bands")
    del keys
    release(spark)
    # a node's text comes from its first document; the node in most buckets is compared first
    central = members.groupBy("node").agg((-F.count(F.lit(1))).alias("weight"))
    homes = listed.join(central.select("node"), "node", "left_semi").groupBy("node").agg(F.min(F.struct("doc_id", "copy")).alias("home"))
    wanted = homes.groupBy("home").agg(F.collect_list("node").alias("wanted")).select("home.*", "wanted")
    sets = docs.join(wanted, ["doc_id", "copy"]).select("text", "wanted").mapInArrow(_chosen_sets(least), "node long, n long, tokens binary").dropDuplicates(["node"])
    sets = stage(sets, "unit-sets", "lz4")
    release(spark)
    bounds = sets.select("node", "n")
    side = lambda s: sets.select(F.col("node").alias(s), F.col("n").alias(f"{s}_n"), F.col("tokens").alias(f"{s}_tokens"))

    def verify(pairs: DataFrame) -> DataFrame:
        near = pairs.join(bounds.toDF("a", "x"), "a").join(bounds.toDF("b", "y"), "b").filter(F.least("x", "y") * 100 >= F.greatest("x", "y") * percent).select("a", "b")
        return near.join(side("a"), "a").join(side("b"), "b").mapInArrow(_similar(percent), "a long, b long")

    found = bucket_links(members.join(central, "node").withColumn("depth", F.lit(1)), sets, verify, percent)
    out = stage(_repeats(listed, found), "repeats")
    for read in (listed, members, sets):
        unstage(read)
    return out


def _repeats(listed: DataFrame, found: DataFrame) -> DataFrame:
    """Units of each class but the first; a class's first is found before the rows are joined."""
    nodes = listed.groupBy("node").agg(F.min(F.struct("doc_id", "copy", "word", "n")).alias("first"), F.count(F.lit(1)).alias("copies"))
    classed = nodes.join(found, "node", "left").withColumn("component", F.coalesce("component", "node"))
    firsts = classed.groupBy("component").agg(F.min("first").alias("head"), F.sum("copies").alias("size")).filter("size > 1")
    heads = stage(classed.join(firsts, "component").select("node", "head"), "heads")
    late = (F.col("doc_id") != F.col("head.doc_id")) | (F.col("copy") != F.col("head.copy")) | (F.col("word") >= F.col("head.word") + F.col("head.n"))
    return listed.join(heads, "node").filter(late).select("doc_id", "copy", "word", "n", F.col("head.doc_id").alias("repeated_id"), F.col("head.word").alias("repeated_word"))


def run_bounds(words: np.ndarray, sizes: np.ndarray, least: int) -> tuple[list[int], list[int]]:
    """Ranges of words (first, past the last) that the units cover, joined where they touch, of `least` words or more."""
    if not len(words):
        return [], []
    order = np.argsort(words, kind="stable")
    starts, ends = words[order], np.maximum.accumulate((words + sizes)[order])
    new = np.ones(len(starts), bool)
    new[1:] = starts[1:] > ends[:-1]
    first = np.flatnonzero(new)
    starts, ends = starts[first], ends[np.append(first[1:], len(new)) - 1]
    long = ends - starts >= least
    return starts[long].tolist(), ends[long].tolist()


def byte_ranges(raw: bytes, starts: np.ndarray, ends: np.ndarray, low: list[int], high: list[int]) -> list[tuple[int, int]]:
    """Byte ranges of ranges of words, with the blanks up to the next word, up to its line break at most.

    starts and ends are the words' bytes. What lies between whole lines goes with them.
    """
    out = []
    for a, b in zip(low, high):
        x, y = int(starts[a]), int(ends[b - 1])
        gap = raw[y : int(starts[b]) if b < len(starts) else len(raw)]
        stop = gap.find(b"\n")
        begins_line = not raw[raw.rfind(b"\n", 0, x) + 1 : x].strip()
        if stop < 0:
            y += len(gap) if b < len(starts) else 0
        elif begins_line:
            y += stop + 1  # the lines are gone, and so is their last break
        out.append((x, y))
    return out


CUT_COLUMNS = ["n_words", "n_bytes", "n_removed", "n_spans", "kept_sha256", "span_starts", "span_ends", "kept_text"]
CUT_TYPES = "n_words long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, span_starts array<long>, span_ends array<long>, kept_text string"


def _cut(least: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in text_slices(batch, "__text"):
                column = part.column(part.schema.get_field_index("__text"))
                w, units = Words(column), part.column(part.schema.get_field_index("__units"))
                data, cuts = w.raw.tobytes(), w.cuts.tolist()
                rows = []
                for d in range(part.num_rows):
                    raw = data[cuts[d] : cuts[d + 1]]
                    a, b = w.first_word[d], w.first_word[d + 1]
                    spans = []
                    if units[d].is_valid:
                        found = np.asarray(units[d].values)
                        spans = byte_ranges(raw, w.starts[a:b] - cuts[d], w.ends[a:b] - cuts[d], *run_bounds(found >> 32, found & 0xFFFFFFFF, least))
                    kept, at = [], 0
                    for x, y in spans:
                        kept.append(raw[at:x])
                        at = y
                    kept = b"".join([*kept, raw[at:]]) if spans else raw
                    rows.append((int(b - a), len(raw), len(raw) - len(kept), len(spans), hashlib.sha256(kept).hexdigest(), [x for x, _ in spans], [y for _, y in spans], kept.decode() if column[d].is_valid else None))
                kinds = [pa.int64()] * 4 + [pa.string(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.string()]
                made = [pa.array(c, k) for c, k in zip(zip(*rows), kinds)]
                others = [c for c in part.schema.names if c not in ("__text", "__units")]
                yield pa.RecordBatch.from_arrays([*[part.column(part.schema.get_field_index(c)) for c in others], *made], [*others, *[f"__{c}" for c in CUT_COLUMNS]])

    return tidy(run)


def without_repeats(docs: DataFrame, least_run: int = LEAST_RUN, **options) -> DataFrame:
    """docs, each column kept, with __n_words, __n_bytes, __n_removed, __n_spans, __kept_sha256, __span_starts, __span_ends, __kept_text.

    Spans are the maximal removed ranges, in bytes of the UTF-8 text; a kept text is the
    rest of it. A null text has no bytes, and a null kept text; rows with a null doc_id stay whole.
    """
    units = repeated_units(docs.select("doc_id", "text"), **options)
    place = F.shiftleft(F.col("word").cast("long"), 32) + F.col("n")
    lists = units.groupBy(F.col("doc_id").alias("__cut_id"), F.col("copy").alias("__cut_copy")).agg(F.collect_set(place).alias("__units"))
    columns = [F.col(f"`{c}`").alias(f"__own_{k}") for k, c in enumerate(docs.columns)]
    rows = docs.select(*columns, F.col("doc_id").cast("long").alias("__doc"), F.xxhash64("text").alias("__copy"), F.col("text").alias("__text"))
    met = rows.join(lists, (F.col("__doc") == F.col("__cut_id")) & (F.col("__copy") == F.col("__cut_copy")), "left")
    names = [f"__own_{k}" for k, c in enumerate(docs.columns) if c != "text"]
    met = met.select(*names, "__text", "__units")
    schema = ", ".join([*[f"{c} {met.schema[c].dataType.simpleString()}" for c in names], *[f"__{x}" for x in CUT_TYPES.split(", ")]])
    out = met.mapInArrow(_cut(least_run), schema)
    return out.select(*[F.col("__kept_text" if c == "text" else f"__own_{k}").alias(c) for k, c in enumerate(docs.columns)], *[f"__{c}" for c in CUT_COLUMNS])


def paragraph_report(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_words, n_bytes, n_removed, n_spans, kept_sha256, span_starts, span_ends of each row of docs.

    n_removed counts bytes of UTF-8; spans are the maximal removed ranges. Texts without
    a repeated unit, empty and null ones, and rows with a null doc_id have no spans.
    """
    out = without_repeats(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), **options)
    return out.select("doc_id", *[F.col(f"__{c}").alias(c) for c in CUT_COLUMNS if c != "kept_text"])


def drop_repeats(docs: DataFrame, **options) -> DataFrame:
    """docs with what an earlier document holds cut out of text, and n_chars (if there) set to what is left.

    All columns and rows stay; a text without a repeat is as before.
    """
    out = without_repeats(docs, **options)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("__n_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars")))
    return out.select(*[F.col(f"`{c}`") for c in docs.columns])
