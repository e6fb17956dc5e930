"""Near-duplicate documents by ProbMinHash signatures, banding and exact verification.

Documents are bags of 5-word shingles, weighted by how often they occur.  Each shingle sends
arrivals of a Poisson process whose rate is its weight to random registers; a register keeps the
earliest arrival's name, and a shingle stops once its next arrival is later than the latest
register.  Two documents agree on a register with the probability Jaccard similarity of their
weights, which is at least their weighted Jaccard similarity.  Bands of registers propose pairs; a
pair is a link if the weighted Jaccard similarity of its two bags (sum of minima over sum of
maxima) is at least `threshold`.  Documents shorter than a shingle are one shingle of all their
words; documents without words link to nothing.

No bucket is expanded into pairs.  Texts with the same words are one class from the start.

1. All members of a bucket are compared with one centre, the member that meets most others over
   all buckets.  Links merge classes; most buckets then hold one class and are settled.
2. In the others, what is outside the bucket's largest class is compared with all members of other
   classes.  Of two members of different classes one is outside the largest, so no pair of a
   bucket is left out.

A comparison is a join's condition, so pairs that are no links never become rows.  It goes from
cheap to exact: sizes allow a link; `AGREE` of all registers agree, by PLANES bits of each, packed
into words; the bags share enough.  A bag is an array with one element for each occurrence of a
shingle, so what two bags share is the size of their intersection.  At a similarity of 0.8 chance
hides one link in 1,500 from the second test and one in 3,000 from the bands; above, far fewer.
A hot centre is one row on one side of a join, and a hot bucket can be split.  Classes are
connected components, found by repeated minimum over neighbours and pointer jumping; neither
links nor labels ever reach the driver.

Texts and shingles are named by hashes (64 bits for texts, 32 for shingles within a bag).  Null
text counts as empty.  Rows of one text share their class, whatever their ids; a class is named by
its least doc_id (null if none has an id).  Empty tables give empty results; of further columns
`classes` takes no notice and `keep_one` returns them as they are, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SpanHasher, broadcast_if, chunks, materialise, mix64, powers, release

SHINGLE = 5
THRESHOLD = 0.8
BANDS = 20
ROWS = 5
REGISTERS = 256  # the bands read the first BANDS * ROWS; a multiple of 64
PLANES = 4
AGREE = 0.72
BATCH_BYTES = 1 << 19


def word_hashes(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the lower-cased words of all texts, and the number of words of each."""
    raw = " \n ".join([" ".join((t or "").lower().split()).replace("\n", " ") for t in texts]).encode("utf-8", "surrogatepass")
    data = np.frombuffer(raw, dtype=np.uint8)
    gap = (data == 0x20) | (data == 0x0A)
    edge = np.diff(np.concatenate([[True], gap, [True]]).astype(np.int8))
    start, end = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
    text_of = np.cumsum(data == 0x0A)[start] if len(start) else np.zeros(0, np.int64)
    return (SpanHasher(data)(start, end) if len(start) else np.zeros(0, np.uint64)), np.bincount(text_of, minlength=len(texts))


def shingles(texts: list[str | None], size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text number, shingle hash, weight) of the distinct shingles, by text and hash; the texts' names."""
    words, n = word_hashes(texts)
    begin = np.cumsum(n) - n
    named = np.zeros(len(words) + 1, dtype=np.uint64)
    np.cumsum(words * powers(0x9E3779B97F4A7C15, int(n.max(initial=0)))[np.arange(len(words)) - np.repeat(begin, n)], out=named[1:])
    node = mix64(named[begin + n] - named[begin] + n.astype(np.uint64)).view(np.int64)
    count = np.where(n >= size, n - size + 1, (n > 0).astype(n.dtype))
    text = np.repeat(np.arange(len(texts)), count)
    at = np.repeat(begin - (np.cumsum(count) - count), count) + np.arange(int(count.sum()))
    left = (begin + n)[text] - at  # words to the end of the text
    h = np.zeros(len(at), dtype=np.uint64)
    for k in range(size):
        inside = left > k
        h *= np.uint64(0x9E3779B97F4A7C15)
        h[inside] += words[at[inside] + k] if len(words) else 0
    h = mix64(h)
    order = np.lexsort((h, text))
    text, h = text[order], h[order]
    head = np.ones(len(h), dtype=bool)
    head[1:] = (h[1:] != h[:-1]) | (text[1:] != text[:-1])
    first = np.flatnonzero(head)
    return text[first], h[first], np.diff(np.append(first, len(h))), node


def signatures(text: np.ndarray, names: np.ndarray, weights: np.ndarray, texts: int, registers: int) -> np.ndarray:
    """texts x registers names of earliest arrivals; 0 for texts without shingles."""
    best = np.full(texts * registers, np.inf)
    out = np.zeros(texts * registers, dtype=np.uint64)
    own, name, weight = text, names.copy(), weights.astype(np.float64)
    state = mix64(names ^ np.uint64(0x5851F42D4C957F2D))
    clock = np.zeros(len(own))
    while len(own):
        state = mix64(state + np.uint64(0x9E3779B97F4A7C15))
        u = ((state >> np.uint64(20)).astype(np.float64) + 0.5) / float(1 << 44)
        clock = clock - np.log(u) / weight
        slot = own * registers + (mix64(state ^ np.uint64(0xC2B2AE3D27D4EB4F)) % np.uint64(registers)).astype(np.int64)
        # earliest arrival of the round at each register
        order = np.lexsort((clock, slot))
        lead = np.ones(len(order), dtype=bool)
        lead[1:] = slot[order[1:]] != slot[order[:-1]]
        win = order[lead]
        sooner = clock[win] < best[slot[win]]
        win = win[sooner]
        best[slot[win]] = clock[win]
        out[slot[win]] = name[win]
        # later arrivals only get later: a shingle stops beyond its text's latest register
        alive = clock < best.reshape(texts, registers).max(axis=1)[own]
        own, name, weight, state, clock = own[alive], name[alive], weight[alive], state[alive], clock[alive]
    return out.reshape(texts, registers)


def mark_planes(signature: np.ndarray) -> np.ndarray:
    """The top PLANES bits of each register: plane after plane, 64 registers a word."""
    top = (signature >> np.uint64(64 - PLANES)).astype(np.uint8)
    return np.concatenate([np.packbits((top >> k) & 1, axis=1).view(np.int64) for k in range(PLANES)], axis=1)


def _lists(values: np.ndarray) -> pa.Array:
    n, each = values.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(0, n * each + 1, each), pa.int32()), pa.array(values.ravel()))


def _signed(bands: int, rows: int, registers: int):
    """node, weight, band keys and mark planes beside the columns before the text, which is last."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            *own, texts = b.columns
            for part in chunks(texts, BATCH_BYTES):
                some = texts.slice(part.start, part.stop - part.start).to_pylist()
                text, h, w, node = shingles(some)
                n = len(some)
                weight = np.bincount(text, w, minlength=n).astype(np.int64)
                every = signatures(text, h, w, n, registers)
                sig = every[:, : bands * rows].reshape(n, bands, rows)
                key = np.zeros((n, bands), dtype=np.uint64)
                for r in range(rows):
                    key = key * np.uint64(0x9E3779B97F4A7C15) + sig[:, :, r]
                key = mix64(key + np.arange(bands, dtype=np.uint64)).view(np.int64)
                yield pa.RecordBatch.from_arrays([*(c.slice(part.start, n) for c in own), pa.array(node), pa.array(weight), _lists(key), _lists(mark_planes(every))], names=[*b.schema.names[:-1], "node", "weight", "bands", "planes"])

    return run


def _bags(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each text's bag: 32-bit names of its shingles, a further name for each further occurrence."""
    for b in batches:
        for part in chunks(b.column(0), BATCH_BYTES):
            some = b.column(0).slice(part.start, part.stop - part.start).to_pylist()
            text, h, w, node = shingles(some)
            nth = np.arange(int(w.sum())) - np.repeat(np.cumsum(w) - w, w)
            names = np.repeat(h, w)
            names[nth > 0] = mix64(names[nth > 0] + nth[nth > 0].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
            edges = np.concatenate([[0], np.cumsum(np.bincount(text, w, minlength=len(some)))]).astype(np.int32)
            bags = pa.ListArray.from_arrays(pa.array(edges), pa.array((names >> np.uint64(32)).astype(np.uint32).view(np.int32)))
            yield pa.RecordBatch.from_arrays([pa.array(node), bags], names=["node", "bag"])


def components(links: DataFrame) -> DataFrame:
    """node and label (the component's least node) of every node in links (a, b)."""
    both = materialise(links.select("a", "b").union(links.select(F.col("b"), F.col("a"))).distinct(), "links")
    label = materialise(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("label")), "labels")
    while True:
        near = both.join(label.withColumnsRenamed({"node": "b", "label": "near"}), "b").groupBy("a").agg(F.min("near").alias("near"))
        hop = label.select(F.col("node").alias("label"), F.col("label").alias("up"))
        new = label.join(near.withColumnRenamed("a", "node"), "node").join(hop, "label", "left")
        new = materialise(new.select("node", F.least("label", "near", F.coalesce("up", "label")).alias("label"), F.col("label").alias("old")), "labels")
        release(label)
        label = new
        if new.where("label <> old").isEmpty():
            release(both)
            return label


def _merge(label: DataFrame, links: DataFrame) -> DataFrame:
    """Labels after further links: the links join labels, whose components relabel the nodes."""
    ends = links.join(label.withColumnsRenamed({"node": "a", "label": "la"}), "a").join(label.withColumnsRenamed({"node": "b", "label": "lb"}), "b")
    joined = materialise(ends.where("la <> lb").select(F.col("la").alias("a"), F.col("lb").alias("b")).distinct(), "merged")
    if joined.isEmpty():
        release(links, joined)
        return label
    found = components(joined)
    to = found.select(F.col("label").alias("to"), F.col("node").alias("label"))
    out = materialise(label.join(to, "label", "left").select("node", F.coalesce("to", "label").alias("label")), "classes")
    release(links, joined, found, label)
    return out


def _agreeing(mine: str, other: str, registers: int) -> Column:
    """Registers whose marks agree."""
    words = registers // 64

    def differing(word: int) -> Column:
        differ = [F.get(mine, F.lit(k * words + word)).bitwiseXOR(F.get(other, F.lit(k * words + word))) for k in range(PLANES)]
        return F.bit_count(reduce(Column.bitwiseOR, differ))

    return F.lit(registers) - sum((differing(i) for i in range(1, words)), differing(0))


def _labelled(docs: DataFrame, threshold: float, bands: int, rows: int, registers: int) -> DataFrame:
    """doc_id, print (of the text), node and label of every row of docs."""
    own = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).select("doc_id", F.xxhash64("text").alias("print"), "text")
    kind = dict(docs.dtypes)["doc_id"]
    signed = materialise(own.mapInArrow(_signed(bands, rows, registers), f"doc_id {kind}, print long, node long, weight long, bands array<long>, planes array<long>"), "signatures")
    every = signed.where("weight > 0").select("node", F.explode("bands").alias("band"))
    # a bucket that holds one content proposes nothing
    shared = every.groupBy("band").agg(F.min("node").alias("lo"), F.max("node").alias("hi"), F.count(F.lit(1)).alias("n")).where("lo <> hi").select("band", "n")
    member = materialise(every.join(shared, "band").groupBy("band", "node").agg(F.first("n").alias("n")), "members")
    met = materialise(member.groupBy("node").agg(F.sum("n").alias("met")), "met")
    # facts of each content in a bucket, and the row whose text stands for it
    lead = F.min(F.struct("doc_id", "print")).alias("lead")
    sketch = signed.join(broadcast_if(met, 16), "node").groupBy("node").agg(lead, *[F.first(c).alias(c) for c in ("weight", "planes")])
    sketch = materialise(sketch, "sketches")
    leads = materialise(sketch.select(F.col("lead.doc_id").alias("lead_id"), F.col("lead.print").alias("lead_print")), "leads")
    is_lead = F.col("doc_id").eqNullSafe(F.col("lead_id")) & (F.col("print") == F.col("lead_print"))
    texts = own.join(broadcast_if(leads, 16), is_lead, "left_semi").select("text")
    bags = texts.mapInArrow(_bags, "node long, bag array<int>").groupBy("node").agg(F.first("bag").alias("bag"))
    facts = materialise(sketch.drop("lead").join(bags, "node"), "facts")
    release(sketch, leads)
    least = round(AGREE * registers)

    def linked(a: str, b: str) -> Column:
        """The nodes whose facts have prefixes a and b are a link; tested from cheap to exact."""
        wa, wb, share = F.col(f"{a}weight"), F.col(f"{b}weight"), F.lit(threshold)
        shared = F.size(F.array_intersect(f"{a}bag", f"{b}bag"))
        return (F.least(wa, wb) >= share * F.greatest(wa, wb)) & (_agreeing(f"{a}planes", f"{b}planes", registers) >= least) & (shared >= share * (wa + wb - shared) - 1e-9)

    def prefixed(df: DataFrame, prefix: str) -> DataFrame:
        return df.withColumnsRenamed({c: f"{prefix}{c}" for c in ("node", "label", "weight", "planes", "bag", "apart")})

    # one centre a bucket: the member that meets most others over all buckets
    centre = member.join(broadcast_if(met, 16), "node").groupBy("band").agg(F.max(F.struct("met", "node"))["node"].alias("centre"))
    stars = member.join(centre, "band").where("node <> centre").select(F.least("node", "centre").alias("a_node"), F.greatest("node", "centre").alias("b_node")).distinct()
    found = stars.join(prefixed(facts, "a_"), "a_node").join(prefixed(facts, "b_"), "b_node").where(linked("a_", "b_"))
    alone = materialise(met.select("node", F.col("node").alias("label")), "classes")
    label = _merge(alone, materialise(found.select(F.col("a_node").alias("a"), F.col("b_node").alias("b")), "links"))
    # buckets that still hold several classes
    spots = member.join(label, "node").select("band", "node", "label")
    sizes = spots.groupBy("band", "label").agg(F.count(F.lit(1)).alias("n"))
    mixed = sizes.groupBy("band").agg(F.max(F.struct("n", "label"))["label"].alias("main"), F.count(F.lit(1)).alias("labels")).where("labels > 1").select("band", "main")
    spots = materialise(spots.join(mixed, "band").select("band", "node", "label", (F.col("label") != F.col("main")).alias("apart")), "spots")
    full = spots.join(facts, "node")
    about = prefixed(full.where("apart"), "c_")
    once = ~F.col("apart") | (F.col("node") < F.col("c_node"))
    found = full.join(about, "band").where((F.col("label") != F.col("c_label")) & once & linked("", "c_"))
    found = found.select(F.least("node", "c_node").alias("a"), F.greatest("node", "c_node").alias("b")).distinct()
    label = _merge(label, materialise(found, "links"))
    release(member, met, facts, spots)
    return signed.select("doc_id", "print", "node").join(broadcast_if(label, 16), "node", "left").withColumn("label", F.coalesce("label", "node"))


def classes(docs: DataFrame, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, registers: int = REGISTERS) -> DataFrame:
    """doc_id, node (names the text's words), class_id (least doc_id of the class) and class_size of every row."""
    named = _labelled(docs, threshold, bands, rows, registers)
    sizes = named.groupBy("label").agg(F.min("doc_id").alias("class_id"), F.count(F.lit(1)).alias("class_size"))
    return named.join(sizes, "label").select("doc_id", "node", "class_id", "class_size")


def keep_one(docs: DataFrame, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, registers: int = REGISTERS) -> DataFrame:
    """One row of each class: the one with the least doc_id, nulls last, and of these the least print.

    Rows are told apart by doc_id and text, so rows that repeat an id with unlike texts all stay,
    and rows that repeat both are one.  Texts move only where they share both with another row.
    """
    named = materialise(_labelled(docs, threshold, bands, rows, registers).select("label", "doc_id", "print"), "labelled")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "print"))
    each = named.groupBy("label").agg(first.alias("one"), F.count(F.lit(1)).alias("n")).where("n > 1")
    chosen = F.col("doc_id").eqNullSafe(F.col("one.doc_id")) & (F.col("print") == F.col("one.print"))
    marked = named.join(each, "label").select("doc_id", "print", chosen.alias("chosen"))
    gone = materialise(marked.where("not chosen").select(F.col("doc_id").alias("gone_id"), F.col("print").alias("gone_print")).distinct(), "gone")
    twice = materialise(marked.where("chosen").groupBy("doc_id", "print").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(F.col("doc_id").alias("gone_id"), F.col("print").alias("gone_print")), "twice")
    whole = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id").alias("own_id"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("own_print"))
    same = F.col("own_id").eqNullSafe(F.col("gone_id")) & (F.col("own_print") == F.col("gone_print"))
    kept = whole.join(broadcast_if(gone, 16), same, "left_anti")
    if twice.isEmpty():
        return kept.select("row.*")
    once = kept.join(broadcast_if(twice, 16), same, "left_anti").select("row")
    return once.unionByName(kept.join(broadcast_if(twice, 16), same, "left_semi").dropDuplicates(["own_id", "own_print"]).select("row")).select("row.*")
