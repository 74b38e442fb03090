"""Quality rules whose thresholds follow the corpus: quantile sketches for each language and source.

Everything is DataFrame expressions. Word windows are compared by 64-bit hashes; a text's
repeated windows are found by sorting its own hashes beside their positions, so no
row is exploded and no text is shuffled.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridchain.llm.shared import stage

#: Separators of words, and signs that count as symbols.
GAPS = "[\\x20\\x09-\\x0D]+"
SYMBOLS = "#*$%&|<>"

#: Rate columns held against the corpus, and whether high values are bad.
RATES = ("symbol_rate", "dup_line_rate", "repeat_rate", "long_word_rate")
#: Rows of thresholds that may be broadcast (about 100 bytes each).
BROADCAST_ROWS = 50_000
#: Copies of the thresholds, and salts of the documents, for a table above that.
SALTS = 64
#: A group of this many rows counts as much as the group around it in its limits; a smaller one counts less.
TRUST = 10
#: A rate is out of range beyond q3 + SPREAD * max(q3 - q1, WIDTH); WIDTH keeps a group of equal values from rejecting the next one.
SPREAD = 6.0
WIDTH = {"symbol_rate": 0.005, "dup_line_rate": 0.02, "repeat_rate": 0.02, "long_word_rate": 0.002}
#: Relative rank error of the quantile sketches is one over this.
ACCURACY = 2000


def with_repeated_places(rows: DataFrame) -> DataFrame:
    """windows, an array of hashes, becomes at: ascending places (from 0) of the values that it holds more than once.

    The whole hash is compared: (hash, place) pairs are sorted and neighbours of equal hash picked.
    """
    rows = rows.withColumn("pairs", F.sort_array(F.transform("windows", lambda h, i: F.struct(h.alias("hash"), i.cast("long").alias("place"))))).drop("windows")
    n = F.size("pairs")
    most = F.greatest(n - 1, F.lit(1))
    both = F.zip_with(F.slice("pairs", 1, most), F.slice("pairs", 2, most), lambda a, b: F.when(a["hash"] == b["hash"], F.array(a["place"], b["place"])))
    places = F.flatten(F.filter(both, lambda x: x.isNotNull()))
    twice = F.when(n >= 2, F.array_sort(F.array_distinct(places)))
    return rows.withColumn("at", twice).drop("pairs")


def with_rule_counts(docs: DataFrame) -> DataFrame:
    """doc_id, lang, source and the counts n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words.

    Null texts have no words. Of repeated word windows the first counts too; a line counts
    when it has a word and equals an earlier line.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", "lang", "source", text.alias("text"))
    rows = rows.withColumn("words", F.filter(F.split("text", GAPS), lambda w: w != ""))
    lines = F.filter(F.split("text", "\n"), lambda x: x.rlike("[^\\x20\\x09-\\x0D]"))
    rows = rows.withColumn("lines", lines)
    rows = rows.withColumns({
        "n_words": F.size("words").cast("long"),
        "word_chars": F.length(F.regexp_replace("text", GAPS, "")).cast("long"),
        "n_symbols": (F.length("text") - F.length(F.translate("text", SYMBOLS, ""))).cast("long"),
        "n_dup_lines": (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long"),
    })
    # hash of each window of three words
    hashed = F.transform("words", lambda w: F.xxhash64(w))
    rows = rows.withColumn("hashed", hashed).drop("words", "lines", "text")
    most = F.greatest(F.size("hashed") - 2, F.lit(1))
    part = lambda k: F.slice("hashed", k, most)
    joined = lambda a, b: F.xxhash64(a, b)
    windows = F.when(F.col("n_words") >= 3, F.zip_with(F.zip_with(part(1), part(2), joined), part(3), joined))
    rows = rows.withColumn("windows", windows).drop("hashed")
    rows = with_repeated_places(rows)
    # words under windows that start at `at`: each adds 3, less what the one before covers
    most = F.greatest(F.size("at") - 1, F.lit(1))
    three, none = F.lit(3).cast("long"), F.lit(0).cast("long")
    steps = F.zip_with(F.slice("at", 1, most), F.slice("at", 2, most), lambda a, b: F.when(b.isNull() | a.isNull(), none).otherwise(F.least(b - a, three)))
    covered = F.when(F.size("at") > 0, F.aggregate(steps, three, lambda total, x: total + x)).otherwise(none)
    return rows.withColumn("n_repeat_words", covered).drop("at")


def _with_rates(rows: DataFrame) -> DataFrame:
    words = F.greatest(F.col("n_words"), F.lit(1))
    return rows.withColumns({
        "base_failed": (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words")),
        "symbol_rate": F.col("n_symbols") / words,
        "dup_line_rate": F.col("n_dup_lines") * 10.0 / words,
        "repeat_rate": F.col("n_repeat_words") / words,
        "long_word_rate": F.greatest(F.col("word_chars") / words / 60.0, F.lit(0.0)),
    })


def rule_thresholds(rows: DataFrame, accuracy: int = ACCURACY) -> DataFrame:
    """lang, source, rows and an upper limit of each rate, by language and source, by language (source null) and for all (both null).

    percentile_approx keeps a mergeable sketch of fixed accuracy for each group in every
    task, so a source with a third of all rows is summed up before the shuffle. Rows that
    fail the base rules take no part. Null languages and sources count as ''.
    """
    rates = rows.filter("not base_failed").withColumns({"lang": F.coalesce("lang", F.lit("")), "source": F.coalesce("source", F.lit(""))})
    sketches = [F.percentile_approx(r, [0.25, 0.75], accuracy).alias(r) for r in RATES]
    limits = [(F.col(r)[1] + SPREAD * F.greatest(F.lit(WIDTH[r]), F.col(r)[1] - F.col(r)[0])).alias(f"{r}_limit") for r in RATES]
    sets = rates.groupingSets([("lang", "source"), ("lang",), ()], "lang", "source")
    return sets.agg(F.count(F.lit(1)).alias("rows"), F.grouping_id().alias("level"), *sketches).select("lang", "source", "rows", "level", *limits)


def group_limits(limits: DataFrame) -> DataFrame:
    """Limits of each language and source, drawn towards those of its language, and these towards those of all.

    A group of n rows weighs n against TRUST, so a rare source follows its language and a large one its own sketch.
    """
    names = [f"{r}_limit" for r in RATES]
    named = lambda level, tag: limits.filter(F.col("level") == level).select(*(["lang"] if level < 3 else []), *(["source"] if level == 0 else []), F.col("rows").alias(f"rows_{tag}"), *[F.col(n).alias(f"{n}_{tag}") for n in names])
    met = named(0, "own").join(named(1, "lang"), "lang").crossJoin(F.broadcast(named(3, "all")))  # one row
    drawn = lambda own, rows, around: (F.col(own) * F.col(rows) + around * TRUST) / (F.col(rows) + TRUST)
    return met.select("lang", "source", *[drawn(f"{n}_own", "rows_own", drawn(f"{n}_lang", "rows_lang", F.col(f"{n}_all"))).alias(n) for n in names])


def quality_rules(docs: DataFrame) -> DataFrame:
    """doc_id, the five counts, base_failed and kept of each row of docs.

    A document that passes the base rules is kept when each of its rates is within the limit
    of its language and source. Null languages and sources form a group of their own; null
    doc_ids keep their rows. Other columns are ignored.
    """
    counts = stage(with_rule_counts(docs), "rules")
    return judged(counts)


def judged(counts: DataFrame) -> DataFrame:
    rows = _with_rates(counts)
    own = stage(group_limits(rule_thresholds(rows)), "limits").select(F.col("lang").alias("for_lang"), F.col("source").alias("for_source"), *[f"{r}_limit" for r in RATES])
    same = (F.coalesce("lang", F.lit("")) == F.col("for_lang")) & (F.coalesce("source", F.lit("")) == F.col("for_source"))
    if own.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS:
        joined = rows.join(F.broadcast(own), same, "left")
    else:
        salted = own.withColumn("for_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        joined = rows.withColumn("salt", F.pmod(F.xxhash64("doc_id", "n_words"), F.lit(SALTS))).join(salted, same & (F.col("salt") == F.col("for_salt")), "left")
    # a group without limits has no row that passes the base rules
    within = F.lit(True)
    for r in RATES:
        within = within & F.coalesce(F.col(r) <= F.col(f"{r}_limit"), F.lit(False))
    return joined.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", (~F.col("base_failed") & within).alias("kept"))


def keep_ruled(docs: DataFrame) -> DataFrame:
    """docs without the documents that the rules reject; all columns stay.

    Rows that share a rejected doc_id all go; rows with a null doc_id stay.
    """
    rejected = stage(quality_rules(docs).filter("not kept and doc_id is not null").select("doc_id").distinct(), "rejected")
    return docs.join(rejected, "doc_id", "left_anti").select(*docs.columns)
