"""Removal of repeated byte strings: shard Burrows-Wheeler transforms merged by interleave refinement.

A string of `span` bytes is repeated when it also starts earlier. Equal strings have equal
least 32-gram hashes, so runs of windows with one least hash are dealt by that hash, and
all occurrences of a string meet in one bucket. Within a bucket, distinct runs are sorted
shard by shard; the shards' transforms are then merged without comparing suffixes again:
each step carries the interleave one symbol pair to the left, keeps the blocks of equal
contexts, and after `span` bytes the blocks are the repeated intervals.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridchain.llm.shared import Packer, blob_rows, bucket_count, forget, group_cuts, mix64, release, stage, text_bytes, text_slices, tidy, unpack
from gridchain.llm.words import _powers, sliding

SPAN = 100
GRAM = 32
#: Values of one bucket, bytes of text in one document bucket, suffixes of one merge and of one shard, about.
BUCKET_VALUES, BUCKET_BYTES, MERGED, SHARD = 1 << 17, 8 << 20, 1 << 19, 1 << 17
NEVER = np.uint64(0xFFFFFFFFFFFFFFFF)


def gram_hashes(raw: np.ndarray, size: int) -> np.ndarray:
    """Hash of each run of `size` bytes."""
    n = len(raw) - size + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    up, down = _powers(len(raw))
    total = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * up[: len(raw)], out=total[1:])
    return mix64((total[size:] - total[:-size]) * down[:n])


def least_runs(raw: np.ndarray, cuts: np.ndarray, span: int = SPAN, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """Runs of windows of `span` bytes with one least gram hash: (hash, row, first, last, loops).

    No window leaves its row; loops tells whether the row holds that gram at two places that
    are least of some window, so that a run may repeat a string within itself.
    """
    n = len(raw) - span + 1
    if n <= 0:
        return tuple(np.zeros(0, t) for t in (np.uint64, np.int64, np.int64, np.int64, bool))
    grams, width = gram_hashes(raw, gram), span - gram + 1
    least = sliding(np.minimum, grams, width)
    # a gram is the least of a window when the largest minimum around it is its own
    padded = np.concatenate([np.zeros(width - 1, np.uint64), least, np.zeros(width - 1, np.uint64)])
    spots = np.flatnonzero(sliding(np.maximum, padded, width) == grams)
    row = np.repeat(np.arange(len(cuts) - 1), np.diff(cuts))[:n]
    valid = np.arange(n) + span <= cuts[row + 1]
    new = np.ones(n, bool)
    new[1:] = (least[1:] != least[:-1]) | (row[1:] != row[:-1])
    starts = np.flatnonzero(new & valid)
    # windows of a row are valid up to a point, so a run ends before the next start or the first invalid window
    last = np.append(starts[1:], n) - 1
    last = np.minimum(last, cuts[row[starts] + 1] - span)
    spot_row = np.searchsorted(cuts, spots, side="right") - 1
    marks = np.sort(grams[spots] ^ mix64(spot_row.astype(np.uint64)))
    doubled = np.unique(marks[1:][marks[1:] == marks[:-1]])
    own = least[starts] ^ mix64(row[starts].astype(np.uint64))
    loops = doubled[np.minimum(np.searchsorted(doubled, own), len(doubled) - 1)] == own if len(doubled) else np.zeros(len(own), bool)
    return least[starts], row[starts], starts, last, loops


def sorted_shard(text: np.ndarray, depth: int) -> np.ndarray:
    """Order of the rotations of text by their first `depth` bytes, by doubling ranks."""
    n = len(text)
    key = np.zeros(n, np.uint64)
    for k in range(8):
        key = (key << np.uint64(8)) | np.roll(text, -k).astype(np.uint64)
    have, rank = 8, None
    while True:
        order = np.argsort(key)
        k = key[order]
        rank = np.empty(n, np.int64)
        rank[order] = np.cumsum(np.concatenate([[0], k[1:] != k[:-1]]))
        if have >= depth or rank[order[-1]] == n - 1:
            return order
        step = min(have, depth - have)
        key = rank.astype(np.uint64) * np.uint64(n) + np.roll(rank, -step).astype(np.uint64)
        have += step


def merge_shards(pairs: list[np.ndarray], depth: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Interleave of sorted shards, given for each the symbol pairs before its rotations, in order.

    Returns (shard of each merged place, block of equal first `depth` bytes, common prefix
    with the place before in pairs of bytes). Every step sorts places by the pair before
    them, keeping their order otherwise, which extends each known context to the left.
    """
    total = sum(map(len, pairs))
    source = np.repeat(np.arange(len(pairs), dtype=np.uint8), [len(p) for p in pairs])
    block = np.zeros(total, np.int32)
    common = np.full(total, depth // 2, np.int32)
    symbols = np.empty(total, np.uint16)
    for step in range(depth // 2):
        for s, p in enumerate(pairs):
            symbols[source == s] = p
        order = np.argsort(symbols, kind="stable")
        source, moved, drawn = source[order], block[order], symbols[order]
        edge = np.ones(total, bool)
        edge[1:] = (drawn[1:] != drawn[:-1]) | (moved[1:] != moved[:-1])
        block = np.cumsum(edge, dtype=np.int32)
        common[np.flatnonzero(edge & (common == depth // 2))] = step
        if block[-1] == total:  # every context is told apart
            break
    return source, block, common


def earlier_windows(blob: np.ndarray, lengths: np.ndarray, docs: np.ndarray, places: np.ndarray, span: int = SPAN, shard: int = SHARD) -> tuple[np.ndarray, np.ndarray]:
    """Windows of strings that are equal to a window at a smaller (doc, place): (string, offset).

    The strings lie one after another in blob; docs and places tell where each begins.
    """
    cuts = np.concatenate([[0], np.cumsum(lengths)])
    ends = np.searchsorted(cuts, np.arange(shard, cuts[-1] + shard, shard), side="left").clip(0, len(lengths))
    bounds = np.unique(np.concatenate([[0], ends, [len(lengths)]]))
    if len(bounds) > 200:  # a shard number is one byte
        bounds = bounds[np.unique(np.linspace(0, len(bounds) - 1, 200).astype(int))]
    pairs, owners, offsets = [], [], []
    for a, b in zip(bounds[:-1], bounds[1:]):
        sizes = lengths[a:b] + 1  # a zero byte after each string
        text = np.zeros(int(sizes.sum()), np.uint8)
        starts = np.cumsum(sizes) - sizes
        owner = np.repeat(np.arange(a, b), sizes)
        offset = np.arange(len(text)) - np.repeat(starts, sizes)
        inside = offset < lengths[owner]
        text[inside] = blob[cuts[a] : cuts[b]]
        order = sorted_shard(text, span)
        before = np.roll(text, 2).astype(np.uint16) << np.uint16(8) | np.roll(text, 1)
        pairs.append(before[order])
        owners.append(owner[order].astype(np.int32))
        offsets.append(offset[order].astype(np.int32))
    source, _, common = merge_shards(pairs, span)
    # a repeated interval is a stretch of places that share a whole string with the place before
    block = np.cumsum(common < span // 2) - 1
    size = np.bincount(block, minlength=int(block[-1]) + 1 if len(block) else 1)
    owner, offset = np.empty(len(source), np.int32), np.empty(len(source), np.int32)
    for s in range(len(pairs)):
        owner[source == s], offset[source == s] = owners[s], offsets[s]
    del pairs, owners, offsets
    valid = (size[block] > 1) & (offset + span <= lengths[owner])
    owner, offset, block = owner[valid], offset[valid], block[valid]
    doc, place = docs[owner], places[owner] + offset
    order = np.lexsort((place, doc, block))
    owner, offset, block = owner[order], offset[order], block[order]
    doc, place = doc[order], place[order]
    first = np.searchsorted(block, block, side="left") if len(block) else block
    later = (doc != doc[first]) | (place != place[first])
    return owner[later], offset[later]


def value_bucket(least: np.ndarray, buckets: int) -> np.ndarray:
    """Bucket of a least hash; least hashes are small numbers, so they are mixed first."""
    return ((mix64(least) >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int32)


def mark_of(docs: np.ndarray, least: np.ndarray) -> np.ndarray:
    """One number for a document and a value that it holds; a false match only costs a comparison."""
    return mix64(docs.view(np.uint64)) ^ least


def _values(buckets: int, span: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = Packer(["keys", "docs"], [np.uint64, np.int64])
        for batch in batches:
            for part in text_slices(batch, "text"):
                least, row, _, _, loops = least_runs(*text_bytes(part.column("text")), span)
                ids = np.asarray(part.column("doc_id"))
                least, row = np.concatenate([least, least[loops]]), np.concatenate([row, row[loops]])
                yield from packer.add(value_bucket(least, buckets), least, ids[row])
        yield from packer.flush()

    return tidy(run)


def _repeated_values(buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, docs = unpack(batches, ["keys", "docs"], [np.uint64, np.int64])
        order = np.lexsort((docs, keys))
        keys, docs = keys[order], docs[order]
        counts = np.diff(group_cuts(keys))
        several = np.repeat(counts > 1, counts)
        keys, docs = keys[several], docs[several]
        if len(keys):
            new = np.ones(len(keys), bool)
            new[1:] = (keys[1:] != keys[:-1]) | (docs[1:] != docs[:-1])
            keys, docs = keys[new], docs[new]
        packer = Packer(["marks"], [np.uint64], 1 << 19)
        for a in range(0, len(keys), 1 << 19):
            s = slice(a, a + (1 << 19))
            yield from packer.add(docs[s].view(np.uint64) % np.uint64(buckets), mark_of(docs[s], keys[s]))
        yield from packer.flush()

    return tidy(run)


def _gather(raw: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Bytes of all given ranges, one after another."""
    shift = np.repeat(starts - (np.cumsum(lengths) - lengths), lengths)
    return raw[np.arange(int(lengths.sum())) + shift]


def content_digests(blob: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """128-bit digest of each string, as two numbers; 96 bits of it travel, and equal ones stand for equal bytes."""
    data, ends = blob.tobytes(), np.cumsum(lengths)
    digests = b"".join(hashlib.blake2b(data[a:b], digest_size=16).digest() for a, b in zip((ends - lengths).tolist(), ends.tolist()))
    return np.frombuffer(digests, np.uint64).reshape(-1, 2)


RUNS = "bucket int, keys binary, high binary, low binary, docs binary, places binary, lengths binary, fresh binary, bytes binary"
RUN_NAMES, RUN_KINDS = ["keys", "high", "low", "docs", "places", "lengths", "fresh"], [np.uint32, np.uint64, np.uint32, np.int64, np.uint32, np.uint32, np.uint8]


#: Marks of a run: its bytes are with it; it may repeat a string within itself; it is later than another copy, which its task knows.
FRESH, LOOPS, LATER = np.uint8(1), np.uint8(2), np.uint8(4)
LOW_BITS = np.uint64(0xFFFFFFFF)


def _packed_runs(held: list[tuple[np.ndarray, ...]], buckets: int) -> pa.RecordBatch:
    """Runs of several slices as one row for each bucket; of equal runs the first keeps its bytes, the others are later copies."""
    least, owner, place, lengths, loops, contents, raw = (np.concatenate(c) for c in zip(*held))
    starts = np.cumsum(lengths) - lengths
    order = np.lexsort((place, owner, contents[:, 1], contents[:, 0]))
    equal = (contents[order][1:] == contents[order][:-1]).all(1)
    head = order[np.maximum.accumulate(np.where(np.concatenate([[False], equal]), 0, np.arange(len(order))))]
    later = np.zeros(len(order), bool)
    later[order] = (owner[order] != owner[head]) | (place[order] != place[head])
    heads = np.zeros(len(order), bool)
    heads[head] = True
    bucket = np.where(later, value_bucket(owner.view(np.uint64), buckets), value_bucket(least, buckets))
    flags = heads * FRESH + (heads & loops) * LOOPS + later * LATER
    order = np.flatnonzero(heads | later)  # a row that repeats its document adds nothing
    order = order[np.argsort(bucket[order], kind="stable")]
    bucket, some = bucket[order], heads[order]
    blob = _gather(raw, starts[order][some], lengths[order][some])
    b_cuts = group_cuts(bucket)
    byte_ends = np.concatenate([[0], np.cumsum(np.where(some, lengths[order], 0))])[b_cuts]
    # a later copy needs no name; beside its bucket a value is told by 32 bits (two values of one name are merely merged together)
    named = [np.where(later, np.uint64(0), c) for c in (mix64(least) & LOW_BITS, contents[:, 0], contents[:, 1] & LOW_BITS)]
    columns = [c.astype(kind, copy=False)[order] for c, kind in zip((*named, owner, place, lengths, flags), RUN_KINDS)]
    arrays = [blob_rows(c, b_cuts) for c in columns]
    return pa.RecordBatch.from_arrays([pa.array(bucket[b_cuts[:-1]]), *arrays, blob_rows(blob, byte_ends)], ["bucket", *RUN_NAMES, "bytes"])


def _runs(buckets: int, span: int, limit: int = 16 << 20):
    """Runs of repeated values, dealt by value, packed as soon as they hold `limit` bytes. Of equal runs in a pack only the first goes
    to the value's bucket, with its bytes; the others are later copies, whatever else there is, and are spread over all buckets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        texts, marks = [], [np.zeros(0, np.uint64)]
        for batch in batches:
            known = np.asarray(batch.column("marks").is_valid())
            if known.any():
                marks += unpack([batch.filter(pa.array(known))], ["marks"], [np.uint64])
            if not known.all():
                texts.append(batch.filter(pa.array(~known)).select(["doc_id", "text"]))
        wanted = np.unique(np.concatenate(marks))
        held: list[tuple[np.ndarray, ...]] = []
        size = 0
        for batch in texts:
            for part in text_slices(batch, "text"):
                raw, cuts = text_bytes(part.column("text"))
                least, row, first, last, loops = least_runs(raw, cuts, span)
                ids = np.asarray(part.column("doc_id"))
                mark = mark_of(ids, np.uint64(0))[row] ^ least
                at = np.searchsorted(wanted, mark)
                chosen = np.flatnonzero(wanted[np.minimum(at, len(wanted) - 1)] == mark) if len(wanted) else np.zeros(0, np.int64)
                if not len(chosen):
                    continue
                least, row, first, loops = least[chosen], row[chosen], first[chosen], loops[chosen]
                lengths = last[chosen] - first + span
                blob = _gather(raw, first, lengths)
                held.append((least, ids[row], first - cuts[row], lengths, loops, content_digests(blob, lengths), blob))
                size += len(blob)
                if size >= limit:
                    yield _packed_runs(held, buckets)
                    held, size = [], 0
        if held:
            yield _packed_runs(held, buckets)

    return tidy(run)


def key_batches(keys: np.ndarray, sizes: np.ndarray, limit: int) -> list[tuple[int, int]]:
    """Ranges of sorted keys that hold about `limit` in all; equal keys stay together."""
    cuts = group_cuts(keys)
    total = np.concatenate([[0], np.cumsum(sizes)])[cuts]
    out, start = [], 0
    for end in range(1, len(cuts)):
        if total[end] - total[start] >= limit or end == len(cuts) - 1:
            out.append((int(cuts[start]), int(cuts[end])))
            start = end
    return out


def _covered(buckets: int, span: int):
    """Ranges of bytes that a bucket finds repeated: docs, starts, ends, dealt by document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        held = list(batches)
        keys, high, low, docs, places, lengths, fresh = unpack(held, RUN_NAMES, RUN_KINDS)
        (blob,) = unpack(held, ["bytes"], [np.uint8])
        del held
        if not len(keys):
            return
        places, lengths = places.astype(np.int64), lengths.astype(np.int64)
        later = (fresh & LATER) > 0
        out_docs, out_starts, out_ends = [docs[later]], [places[later]], [places[later] + lengths[later]]
        keys, high, low, docs, places, lengths, fresh = (c[~later] for c in (keys, high, low, docs, places, lengths, fresh))
        loops = (fresh & LOOPS) > 0
        starts = np.cumsum(lengths) - lengths
        order = np.lexsort((low, high))
        new = np.ones(len(order), bool)
        new[1:] = (high[order][1:] != high[order][:-1]) | (low[order][1:] != low[order][:-1])
        contents = np.empty(len(order), np.int64)
        contents[order] = np.cumsum(new)
        del high, low, new
        order = np.lexsort((places, docs, contents))
        text_at = starts[order][group_cuts(contents[order])[:-1]]  # of each content the first copy's bytes
        contents, docs, places, lengths, keys, loops = contents[order], docs[order], places[order], lengths[order], keys[order], loops[order]
        cuts = group_cuts(contents)
        head = cuts[:-1]
        first = np.repeat(head, np.diff(cuts))
        # rows that repeat a document hold its strings at the same places: no string is earlier than itself
        later = (docs != docs[first]) | (places != places[first])
        out_docs, out_starts, out_ends = [*out_docs, docs[later]], [*out_starts, places[later]], [*out_ends, places[later] + lengths[later]]
        # a value with one content needs no merge, unless that content may repeat within itself
        key, count = np.unique(keys[head], return_counts=True)
        looping = np.bincount(np.searchsorted(key, keys[head]), np.maximum.reduceat(loops, head), len(key)) > 0
        open_keys = ((count > 1) | looping)[np.searchsorted(key, keys[head])]
        chosen = head[open_keys]
        by_key = np.argsort(keys[chosen], kind="stable")
        chosen, text_at = chosen[by_key], text_at[open_keys][by_key]
        # values are independent of each other, so they are merged in batches of a bounded size
        for a, b in key_batches(keys[chosen], lengths[chosen], MERGED):
            part = chosen[a:b]
            size = lengths[part]
            owner, offset = earlier_windows(_gather(blob, text_at[a:b], size), size, docs[part], places[part], span)
            order = np.lexsort((offset, owner))
            owner, offset = owner[order], offset[order]
            new = np.ones(len(owner), bool)
            new[1:] = (owner[1:] != owner[:-1]) | (offset[1:] != offset[:-1] + 1)
            first = np.flatnonzero(new)
            last = np.append(first[1:], len(owner)) - 1
            if len(first):
                at = part[owner[first]]
                out_docs.append(docs[at])
                out_starts.append(places[at] + offset[first])
                out_ends.append(places[at] + offset[last] + span)
        packer = Packer(["docs", "starts", "ends"], [np.int64, np.int64, np.int64], 1 << 19)
        d, s, e = map(np.concatenate, (out_docs, out_starts, out_ends))
        for a in range(0, len(d), 1 << 19):
            z = slice(a, a + (1 << 19))
            yield from packer.add(d[z].view(np.uint64) % np.uint64(buckets), d[z], s[z], e[z])
        yield from packer.flush()

    return tidy(run)


def merge_ranges(starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal ranges that the given ones cover; ranges that touch are one."""
    order = np.argsort(starts, kind="stable")
    starts, ends = starts[order], np.maximum.accumulate(ends[order])
    new = np.ones(len(starts), bool)
    new[1:] = starts[1:] > ends[:-1]
    first = np.flatnonzero(new)
    return starts[first], ends[np.append(first[1:], len(starts)) - 1]


def _cut(with_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        texts, parts = [], [[np.zeros(0, np.int64)] for _ in range(3)]
        for batch in batches:
            known = np.asarray(batch.column("docs").is_valid())
            if known.any():
                for p, c in zip(parts, unpack([batch.filter(pa.array(known))], ["docs", "starts", "ends"], [np.int64] * 3)):
                    p.append(c)
            if not known.all():
                texts.append(batch.filter(pa.array(~known)).select(["doc_id", "own_id", "text"]))
        docs, starts, ends = map(np.concatenate, parts)
        order = np.argsort(docs, kind="stable")
        docs, starts, ends = docs[order], starts[order], ends[order]
        for batch in texts:
            for part in text_slices(batch, "text"):
                raw, cuts = text_bytes(part.column("text"))
                ids = np.asarray(part.column("doc_id"))
                low, high = np.searchsorted(docs, ids), np.searchsorted(docs, ids, side="right")
                rows = []
                for i in range(len(ids)):
                    text = raw[cuts[i] : cuts[i + 1]]
                    a, b = merge_ranges(starts[low[i] : high[i]], ends[low[i] : high[i]]) if high[i] > low[i] else (docs[:0], docs[:0])
                    keep = np.ones(len(text), bool)
                    for x, y in zip(a.tolist(), b.tolist()):
                        keep[x:y] = False
                    kept = text[keep].tobytes()
                    rows.append((len(text), len(text) - len(kept), len(a), hashlib.sha256(kept).hexdigest(), a.tolist() if with_text else None, b.tolist() if with_text else None, kept if with_text else None))
                columns = list(zip(*rows))
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary()]
                yield pa.RecordBatch.from_arrays([part.column("own_id"), *[pa.array(c, k) for c, k in zip(columns, kinds)]], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "span_starts", "span_ends", "kept_bytes"])

    return tidy(run)


def remove_repeats(docs: DataFrame, span: int = SPAN, with_text: bool = False) -> DataFrame:
    """Cut every byte that a `span`-byte string covers which also starts earlier.

    Returns doc_id, n_bytes, n_removed, n_spans, kept_sha256, and with_text also span_starts,
    span_ends, kept_bytes. Earlier is a smaller doc_id or an earlier start in the same
    document; strings are judged on the input. Null texts are empty. Rows that repeat a doc_id
    are one document: a string at the same place in two of them is one string, and is not
    earlier than itself. Rows with a null doc_id come after all others (doc_ids are below 2^62),
    in an order fixed by their texts; those with equal texts are one document. span is even.
    """
    spark = docs.sparkSession
    unnamed = F.lit(1 << 62).bitwiseOR(F.xxhash64("text").bitwiseAND(F.lit((1 << 62) - 1)))
    rows = docs.select(F.col("doc_id").cast("long").alias("own_id"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.select(F.coalesce("own_id", unnamed).alias("doc_id"), "own_id", "text")
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    by_value, by_doc = bucket_count(spark, size // 32, BUCKET_VALUES), bucket_count(spark, size, BUCKET_BYTES)
    values = rows.mapInArrow(_values(by_value, span), "bucket int, keys binary, docs binary").repartition(by_value, "bucket")
    wanted = stage(values.mapInArrow(_repeated_values(by_doc), "bucket int, marks binary"), "repeated", "lz4")
    del values
    release(spark)
    texts = rows.select(F.pmod("doc_id", F.lit(by_doc)).cast("int").alias("bucket"), "doc_id", "own_id", "text")
    nothing = lambda *names: [F.lit(None).cast("binary").alias(n) for n in names]
    no_text = [F.lit(None).cast("long").alias("doc_id"), F.lit(None).cast("long").alias("own_id"), F.lit(None).cast("string").alias("text")]
    met = texts.select("bucket", "doc_id", "own_id", "text", *nothing("marks")).union(wanted.select("bucket", *no_text, "marks"))
    runs = met.repartition(by_doc, "bucket").mapInArrow(_runs(by_value, span), RUNS).repartition(by_value, "bucket")
    ranges = stage(runs.mapInArrow(_covered(by_doc, span), "bucket int, docs binary, starts binary, ends binary"), "ranges")
    del met, runs
    release(spark)
    met = texts.select("bucket", "doc_id", "own_id", "text", *nothing("docs", "starts", "ends")).union(ranges.select("bucket", *no_text, "docs", "starts", "ends"))
    out = met.repartition(by_doc, "bucket").mapInArrow(_cut(with_text), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, span_starts array<long>, span_ends array<long>, kept_bytes binary")
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", *["span_starts", "span_ends", "kept_bytes"] * with_text)
