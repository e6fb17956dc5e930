"""Document quality with thresholds that adapt to language and source.

A narrow pass measures each text.  The measures of the texts that pass the base rules go into
quantile sketches, one for each (language, source) and measure: histograms whose bins grow by a
fixed factor, so that every quantile is known within `ACCURACY` of its value.  Counts of bins add
up, so sketches merge exactly, in any order and with the same result; languages and the whole
corpus are sums of the groups' sketches and no row is read twice.  Sketches are summed map side,
so a hot source costs as many rows a task as it has bins.

A group's fence lies beyond its upper quantile by a multiple of the distance between that quantile
and its mirror; the multiple puts the fence of a normally distributed measure `REACH` standard
deviations above its mean, whichever quantile is used.  `TAILS` names the quantile of each measure.
No number fixes a fence: a group without LEAST rows, or without distance between its two
quantiles, takes its language's fence, a language without them the corpus's, and a corpus without
them has none.  Texts beyond a fence, or that fail the base rules, are rejected.

Null text has no words and fails; null language or source is a group of its own; repeated rows
count as often as they occur.  Empty tables give empty results.  `filter_documents` returns all
columns as they are, whatever their names.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from statistics import NormalDist

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from .common import broadcast_if, materialise

ACCURACY = 0.005
GROWTH = (1 + ACCURACY) / (1 - ACCURACY)
REACH = 4.7
LEAST = 30
#: Measures that may not exceed their fence, and the quantile that it starts from: the more of the
#: good texts repeat lines or phrases, the further out.
TAILS = {"symbol_ratio": 0.95, "repeat_ratio": 0.99, "dup_line_ratio": 0.99, "word_length": 0.75}

_WORD = re.compile("[^\x20\x09-\x0d]+")
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")
SYMBOLS = "#*$%&|<>"


def repeat_words(words: list[str]) -> int:
    """Words inside 3-word windows that occur at least twice, first occurrences included."""
    windows = list(zip(words, words[1:], words[2:], strict=False))
    if len(set(windows)) == len(windows):
        return 0
    count = Counter(windows)
    inside = bytearray(len(words))
    for i, w in enumerate(windows):
        if count[w] > 1:
            inside[i : i + 3] = b"\1\1\1"
    return sum(inside)


def measure(text: str | None) -> tuple[int, ...]:
    text = text or ""
    words = _WORD.findall(text)
    lines = [x for x in text.split("\n") if _WORD.search(x)]
    return len(words), sum(map(len, words)), sum(map(text.count, SYMBOLS)), len(lines) - len(set(lines)), repeat_words(words), len(lines)


@F.arrow_udf(StructType([StructField(c, LongType()) for c in COUNTS]))
def measures_of(texts: pa.Array) -> pa.Array:
    got = [measure(t) for t in texts.to_pylist()]
    return pa.StructArray.from_arrays([pa.array([g[i] for g in got], pa.int64()) for i in range(len(COUNTS))], list(COUNTS))


def _measured(docs: DataFrame, **kept: Column) -> DataFrame:
    """kept columns, lang, source, measures (a struct) and base_failed."""
    # a deterministic function would be run again for a filter that is pushed below it
    once = measures_of.asNondeterministic()
    own = docs.select(*[c.alias(n) for n, c in kept.items()], "lang", "source", once(F.col("text").cast("string")).alias("m"))
    words = F.col("m.n_words")
    return own.withColumn("base_failed", (words < 50) | (100 * F.col("m.n_repeat_words") > 50 * words))


def _ratio(measure: str) -> Column:
    words, lines = F.greatest("m.n_words", F.lit(1)), F.greatest("m.n_lines", F.lit(1))
    return {"symbol_ratio": F.col("m.n_symbols") / words, "repeat_ratio": F.col("m.n_repeat_words") / words, "dup_line_ratio": F.col("m.n_dup_lines") / lines, "word_length": F.col("m.word_chars") / words}[measure]


def sketches(measured: DataFrame) -> DataFrame:
    """lang, source, measure, bin and n; bin b holds values up to GROWTH ** b, a null bin holds zeros."""
    each = F.explode(F.array(*[F.struct(F.lit(m).alias("measure"), _ratio(m).alias("value")) for m in TAILS]))
    long = measured.where("not base_failed").select("lang", "source", each.alias("x")).select("lang", "source", "x.*")
    at = F.when(F.col("value") > 0, F.ceil(F.log("value") / F.lit(math.log(GROWTH))).cast("int"))
    return long.groupBy("lang", "source", "measure", at.alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def _reach(q: float) -> float:
    z = NormalDist().inv_cdf(q)
    return (REACH - z) / (2 * z)


def _fences(sketch: DataFrame, *group: str) -> DataFrame:
    """group, measure and fence (null where the group has none) from merged sketches."""
    own = sketch.groupBy(*group, "measure", "bin").agg(F.sum("n").alias("n"))
    # a window holds the bins of one sketch
    upto = own.withColumn("upto", F.sum("n").over(Window.partitionBy(*group, "measure").orderBy(F.col("bin").asc_nulls_first())))
    value = F.coalesce(F.lit(2 / (1 + GROWTH)) * F.pow(F.lit(GROWTH), "bin"), F.lit(0.0))
    tail = F.create_map(*[x for m, q in TAILS.items() for x in (F.lit(m), F.lit(q))])[F.col("measure")]
    reach = F.create_map(*[x for m, q in TAILS.items() for x in (F.lit(m), F.lit(_reach(q)))])[F.col("measure")]
    points = upto.groupBy(*group, "measure").agg(F.max("upto").alias("rows"), F.array_sort(F.collect_list(F.struct("upto", value.alias("value")))).alias("bins"))
    at = lambda q: F.filter("bins", lambda b: b["upto"] >= q * F.col("rows"))[0]["value"]
    found = points.select(*group, "measure", "rows", at(1 - tail).alias("low"), at(tail).alias("high"), reach.alias("reach"))
    fence = F.when((F.col("rows") >= LEAST) & (F.col("high") > F.col("low")), F.col("high") + F.col("reach") * (F.col("high") - F.col("low")))
    return found.select(*group, "measure", fence.alias("fence"))


def thresholds(measured: DataFrame) -> DataFrame:
    """group_lang, group_source and fences (measure to fence) of each (lang, source)."""
    own = materialise(sketches(measured), "sketches")
    group = _fences(own, "lang", "source").withColumnRenamed("fence", "by_group")
    lang = _fences(own, "lang").select(F.col("lang").alias("lang_"), F.col("measure").alias("measure_"), F.col("fence").alias("by_lang"))
    whole = _fences(own).select(F.col("measure").alias("measure__"), F.col("fence").alias("by_all"))
    wide = group.join(lang, F.col("lang").eqNullSafe(F.col("lang_")) & (F.col("measure") == F.col("measure_"))).join(whole, F.col("measure") == F.col("measure__"))
    named = F.struct("measure", F.coalesce("by_group", "by_lang", "by_all").alias("fence"))
    each = wide.groupBy(F.col("lang").alias("group_lang"), F.col("source").alias("group_source")).agg(F.map_from_entries(F.collect_list(named)).alias("fences"))
    return broadcast_if(materialise(each, "fences"), 400)


def judge(measured: DataFrame, fences: DataFrame) -> DataFrame:
    """Adds fences and kept to measured rows; groups without a row that passes the base rules need none."""
    same = F.col("lang").eqNullSafe(F.col("group_lang")) & F.col("source").eqNullSafe(F.col("group_source"))
    beyond = F.lit(False)
    for m in TAILS:
        beyond = beyond | F.coalesce(_ratio(m) > F.col("fences")[m], F.lit(False))
    return measured.join(fences, same, "left").withColumn("kept", ~F.col("base_failed") & ~beyond)


def assess(docs: DataFrame) -> DataFrame:
    """doc_id, lang, source, counts, ratios, fences, base_failed and kept of each document."""
    measured = materialise(_measured(docs, doc_id=F.col("doc_id")), "measures")
    judged = judge(measured, thresholds(measured))
    return judged.select("doc_id", "lang", "source", "m.*", *[_ratio(m).alias(m) for m in TAILS], "fences", "base_failed", "kept")


def filter_documents(docs: DataFrame) -> DataFrame:
    """The kept documents with all their columns; texts don't move for it.

    The measures are taken again beside the text, which costs less than a shuffle of the texts.
    """
    fences = thresholds(materialise(_measured(docs), "measures"))
    whole = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
    return judge(_measured(docs, row=whole), fences).where("kept").select("row.*")
