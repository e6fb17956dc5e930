"""Benchmark decontamination by spaced seeds, in DataFrame functions only.

A seed is a window of `SPAN` tokens of which a fixed mask reads some; two passages that differ in
unread positions still share the seed.  The masks leave out every pair of positions, so a window
with two substitutions, wherever they are, keeps a seed.  An item of n tokens may differ in n / 5;
n // 15 + 1 disjoint windows can't all have three of those, so seeds of that many windows lose
nothing.  Only 15 to 19 tokens have no room: there two windows overlap by five, and if neither
keeps a seed by this count, all three differ in the overlap and the first five tokens, a mask of
their own, agree.  Seeds of every benchmark item are joined with seeds of the
corpus, and each hit is verified: the item is laid over the text at the hit's offset, and the text
is contaminated if at least `MIN_MATCH` of the item's tokens agree there.

Most corpus windows are ruled out before any join by two sieves, bitmaps of a fixed size made from
the benchmark: one over the three adjacent tokens that each mask has, one over whole seeds.  A sieve has no false negatives;
what passes by chance fails the join.  Windows that pass are few numbers each, and meet the
benchmark's seeds by equi-join; the benchmark is broadcast only if its seed count is below
`BROADCAST_SEEDS`, otherwise the engine shuffles both sides.  Hits of one text, item and offset are
one; the texts that have any are read once more and the items laid over them.

Tokens are the maximal runs of letters and digits of the lower-cased text.  Items with fewer
tokens than `SPAN` are compared as exact runs of all their tokens: the run is the seed, and its first
token is sieved.  Null text has no tokens; items without tokens are ignored; repeated items report
as themselves; rows of one text are verified once and each reported.  Empty tables give empty
results; further columns don't matter, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import broadcast_if, materialise

#: Positions that each mask reads.  Each pair of positions is unread by some mask.
MASKS = ((0, 1, 2, 3, 4), (2, 5, 6, 7, 8), (3, 4, 5, 6, 9), (3, 4, 7, 8, 9), (0, 1, 5, 6, 7), (0, 1, 2, 8, 9))
LEADS = tuple(next(o for o in m if {o + 1, o + 2} <= set(m)) for m in MASKS)  # of three adjacent positions
SPAN = 10
MIN_MATCH = 0.8
SIEVE_BITS = 1 << 20
BROADCAST_SEEDS = 2_000_000


def tokens(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda t: t != "")


def _mask_hash(h: Column, i: Column, mask: tuple[int, ...], salt: int) -> Column:
    return F.xxhash64(*[F.get(h, i + F.lit(o)) for o in mask], F.lit(salt))


def _lead_hash(h: Column, i: Column) -> Column:
    return F.xxhash64(F.get(h, i), F.get(h, i + F.lit(1)), F.get(h, i + F.lit(2)))


def _run_lead(h: Column, i: Column) -> Column:
    return F.xxhash64(F.get(h, i), F.lit(-1))


def _run_hash(h: Column, i: Column, n: int) -> Column:
    return F.xxhash64(*[F.get(h, i + F.lit(o)) for o in range(n)], F.lit(-n))


def _bit(sieve: Column, value: Column) -> Column:
    at = F.pmod(value, F.lit(SIEVE_BITS))
    return F.getbit(F.get(sieve, F.shiftright(at, 6).cast("int")), F.pmod(at, F.lit(64)).cast("int")) == 1


def _sieve(values: DataFrame) -> Column:
    """A bitmap of SIEVE_BITS bits as a constant array of longs, from one column `v`."""
    at = values.select(F.pmod("v", F.lit(SIEVE_BITS)).alias("at")).distinct()
    words = at.groupBy(F.shiftright("at", 6).cast("int").alias("w")).agg(F.expr("bit_or(shiftleft(1L, cast(pmod(at, 64) AS int)))").alias("bits"))
    bits = ["0"] * (SIEVE_BITS >> 6)
    for w, b in words.collect():  # SIEVE_BITS / 64 rows at most
        bits[w] = str(b)
    return F.split(F.lit(",".join(bits)), ",").cast("array<bigint>")  # folded to a literal once


def item_seeds(benchmark: DataFrame, key: str = "item_id") -> DataFrame:
    """item, item_print, item_pos, lead and seed of each chosen window and mask of each item.

    Items under SPAN tokens have one seed, their whole run.
    """
    own = benchmark.select(F.col(key).alias("item"), tokens(F.col("text")).alias("t")).where(F.size("t") > 0)
    own = own.select("item", F.xxhash64("t").alias("item_print"), F.transform("t", lambda t: F.xxhash64(t)).alias("h"))
    kept = ["item", "item_print"]
    step = F.when(F.size("h") < 2 * SPAN, SPAN // 2).otherwise(SPAN)
    at = own.where(F.size("h") >= SPAN).select(*kept, "h", F.explode(F.transform(F.sequence(F.lit(0), F.expr("size(h) div 15").cast("int")), lambda i: i * step)).alias("item_pos"))
    seeds = F.explode(F.array(*[F.struct(_lead_hash(F.col("h"), F.col("item_pos") + F.lit(o)).alias("lead"), _mask_hash(F.col("h"), F.col("item_pos"), m, k).alias("seed")) for k, (m, o) in enumerate(zip(MASKS, LEADS, strict=True))]))
    long = at.select(*kept, "item_pos", seeds.alias("s")).select(*kept, "item_pos", "s.*")
    run = F.coalesce(*[F.when(F.size("h") == n, _run_hash(F.col("h"), F.lit(0), n)) for n in range(1, SPAN)])
    short = own.where(F.size("h") < SPAN).select(*kept, F.lit(0).alias("item_pos"), _run_lead(F.col("h"), F.lit(0)).alias("lead"), run.alias("seed"))
    return long.unionByName(short)


def _let(value: Column, body) -> Column:
    """body(value) with the value computed once a row, however often a lambda reads it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _windows(text: Column, lead_sieve: Column, seed_sieve: Column, runs: list[int]) -> Column:
    """Array of (pos, seed) of the windows that pass both sieves.

    One expression, exploded as outer: a filter on it would be pushed down and take it apart.
    """

    def windows(t: Column, h: Column) -> Column:
        last = F.size(t) - 3
        spots = F.when(last >= 0, F.sequence(F.lit(0), F.greatest(last, F.lit(0)))).otherwise(F.array().cast("array<int>"))
        led = F.filter(spots, lambda i: _bit(lead_sieve, _lead_hash(h, i)))
        # windows may reach beyond the text, where nothing agrees
        every = F.flatten(F.transform(led, lambda i: F.array(*[F.struct((i - F.lit(o)).alias("pos"), _mask_hash(h, i - F.lit(o), m, k).alias("seed")) for k, (m, o) in enumerate(zip(MASKS, LEADS, strict=True))])))
        if runs:  # lengths of the short items
            begun = F.filter(F.transform(t, lambda x, i: i), lambda i: _bit(lead_sieve, _run_lead(h, i)))
            every = F.concat(every, F.flatten(F.transform(begun, lambda i: F.array(*[F.struct(i.alias("pos"), _run_hash(h, i, n).alias("seed")) for n in runs]))))
        return F.filter(every, lambda w: _bit(seed_sieve, w["seed"]))

    return _let(tokens(text), lambda t: _let(F.transform(t, lambda x: F.xxhash64(x)), lambda h: windows(t, h)))


def _share(text: str, offset: Column) -> Column:
    """Share of item_tokens that agree with the tokens of the array `text` from offset on."""
    laid = F.transform("item_tokens", lambda x, i: F.when((offset + i >= 0) & (F.get(F.col(text), offset + i) == x), F.lit(1)).otherwise(F.lit(0)))
    return F.aggregate(laid, F.lit(0), lambda a, x: a + x) / F.size("item_tokens")


def hits(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", item_key: str = "item_id", min_match: float = MIN_MATCH) -> DataFrame:
    """key, item, start (token of the text where the item begins) and matched share, verified."""
    if min_match < MIN_MATCH:
        raise ValueError(f"the seeds lose nothing from a share of {MIN_MATCH} on, not from {min_match}")
    own = docs.select(F.col(key).alias("key"), F.xxhash64("text").alias("text_print"), "text")
    seeds = item_seeds(benchmark, item_key)
    sized = benchmark.select(F.size(tokens(F.col("text"))).alias("n")).where("n > 0")
    size = sized.agg(F.sum(F.when(F.col("n") >= SPAN, F.expr("n div 15 + 1") * len(MASKS)).otherwise(1)).alias("seeds"), F.array_sort(F.collect_set(F.when(F.col("n") < SPAN, F.col("n")))).alias("runs")).first()
    count = size["seeds"] or 0
    if not count:
        return own.select(F.col("key").alias(key), F.lit(None).cast(dict(benchmark.dtypes)[item_key]).alias("item"), F.lit(0).alias("start"), F.lit(0.0).alias("share")).where(F.lit(False))
    lead_sieve = _sieve(seeds.select(F.col("lead").alias("v")))
    seed_sieve = _sieve(seeds.select(F.col("seed").alias("v")))
    found = own.select("key", "text_print", F.explode_outer(_windows(F.col("text"), lead_sieve, seed_sieve, size["runs"])).alias("w")).select("key", "text_print", "w.*")
    right = F.broadcast(seeds) if count <= BROADCAST_SEEDS else seeds
    met = found.join(right, "seed").select("key", "text_print", "item", "item_print", (F.col("pos") - F.col("item_pos")).alias("start"))
    met = materialise(met.distinct(), "seed-hits")
    prints = materialise(met.select("text_print").distinct(), "hit-texts")
    texts = own.select("text_print", "text").join(broadcast_if(prints, 8), "text_print", "left_semi").dropDuplicates(["text_print"]).select("text_print", tokens(F.col("text")).alias("text_tokens"))
    items = benchmark.select(tokens(F.col("text")).alias("item_tokens")).where(F.size("item_tokens") > 0).withColumn("item_print", F.xxhash64("item_tokens")).dropDuplicates(["item_print"])
    laid = met.select("text_print", "item_print", "start").distinct().join(items, "item_print").join(texts, "text_print")
    least = F.when(F.size("item_tokens") < SPAN, 1.0).otherwise(min_match)
    shares = laid.select("text_print", "item_print", "start", _share("text_tokens", F.col("start")).alias("share"), least.alias("least")).where("share >= least").drop("least")
    return met.join(shares, ["text_print", "item_print", "start"]).select(F.col("key").alias(key), "item", "start", "share").distinct()


def contaminated(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", item_key: str = "item_id") -> DataFrame:
    """key, items (sorted) and best share of each contaminated document; others have no row."""
    found = hits(docs, benchmark, key, item_key).groupBy(key, "item").agg(F.max("share").alias("share"))
    return found.groupBy(key).agg(F.array_sort(F.collect_set("item")).alias("items"), F.max("share").alias("share"))


def decontaminate(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", item_key: str = "item_id") -> DataFrame:
    """The documents that hold no benchmark item, with all their columns."""
    bad = materialise(hits(docs, benchmark, key, item_key).select(F.col(key).alias("bad")).distinct(), "contaminated")
    whole = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col(f"`{key}`").alias("own"))
    return whole.join(broadcast_if(bad, 16), F.col("own").eqNullSafe(F.col("bad")), "left_anti").select("row.*")


ORACLE_MASKS = ((0, 1, 3, 4, 6, 9), (0, 1, 2, 5, 7, 8), (0, 1, 4, 5, 8, 9))

#: The same rule for DuckDB, but only where a seed of one of ORACLE_MASKS agrees and for items of SPAN
#: tokens or more: it misses some edited items; the tests lay items over texts without seeds.
ORACLE_SQL = f"""
WITH docs AS (
  SELECT doc_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\\p{{L}}\\p{{N}}]+'), lambda x: x <> '') AS t FROM documents
), items AS (
  SELECT item_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\\p{{L}}\\p{{N}}]+'), lambda x: x <> '') AS it FROM benchmark
), masks AS (
  SELECT unnest([{", ".join("[" + ", ".join(str(o) for o in m) + "]" for m in ORACLE_MASKS)}]) AS mask
), item_seeds AS (
  SELECT item_id, it, p, mask, list_transform(mask, lambda o: it[p + o + 1]) AS seed
  FROM (SELECT item_id, it, unnest(range(len(it) - {SPAN} + 1)) AS p FROM items WHERE len(it) >= {SPAN}), masks
), doc_seeds AS (
  SELECT doc_id, p, mask, list_transform(mask, lambda o: t[p + o + 1]) AS seed
  FROM (SELECT doc_id, t, unnest(range(len(t) - {SPAN} + 1)) AS p FROM docs WHERE len(t) >= {SPAN}), masks
), met AS (
  SELECT DISTINCT d.doc_id, i.item_id, d.p - i.p AS start FROM doc_seeds d JOIN item_seeds i ON d.mask = i.mask AND d.seed = i.seed
), laid AS (
  SELECT m.doc_id, m.item_id,
         len(list_filter(range(len(i.it)), lambda k: m.start + k >= 0 AND d.t[m.start + k + 1] = i.it[k + 1])) / len(i.it) AS share
  FROM met m JOIN docs d USING (doc_id) JOIN items i USING (item_id)
), bad AS (
  SELECT DISTINCT doc_id, item_id FROM laid WHERE share >= {MIN_MATCH}
)
SELECT doc_id, string_agg(item_id::VARCHAR, ',' ORDER BY item_id) AS items, count(*)::BIGINT AS n_items FROM bad GROUP BY doc_id
"""
