"""Repeated byte passages across documents, by threshold-bounded interval expansion.

A byte goes if a `min_len`-byte string covering it also starts in a document with a smaller
doc_id.  The plan has four steps and ships each passage to one place only:

1. *Anchors.*  Each window of `min_len` bytes names the smallest-hashed 16-byte gram inside it.
   Equal windows name equal grams, so equal strings meet wherever grams meet.  Runs of windows
   with one anchor are handled together.  Two equal windows also agree on the anchor and all bytes
   to one of its sides, out to half of what a window has besides the gram.  Blocks of documents
   send these two longer grams of their runs, as hashes, each once.
2. *Shared grams* come back to the blocks that hold them.
3. *Segments* (a run and the bytes its windows reach) with a shared gram go, once per block and
   content, to the anchor's bucket.  There a Burrows-Wheeler transform is built over the
   segments and its intervals are widened breadth first by backward extension: level l settles
   every neighbouring pair that shares exactly l bytes, and the search stops at `min_len`.
   Pairs left unsettled share at least `min_len` bytes; such a stretch of suffixes is one
   repeated string, and its least doc_id is recorded.
4. The owners' blocks read these minima and cut the spans.

Hot passages cost one row per block, never one per document; nothing is capped or sampled.
Memory in a task is a block of about 8 MB of text (or one longer document), or the distinct
segments around one anchor.  Null text counts as empty; a null doc_id has no order, so such
rows neither lose bytes nor make others lose them.  Rows that repeat a doc_id do not affect one
another, since neither id is smaller.  Columns other than doc_id and text are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SpanHasher, distinct, member, mix64, parts_for, text_bytes

MIN_LEN = 50
GRAM = 16
BLOCK_BYTES = 8 << 20
BATCH_BYTES = 1 << 18
INDEX_BYTES = 1 << 18
SEP = 0xFF  # never a byte of UTF-8
_NO_DOC = np.iinfo(np.int64).max


def _gram_hashes(data: np.ndarray) -> np.ndarray:
    """Hash of the 16 bytes that start at each position, by doubling."""
    h = data.astype(np.uint64)
    h += np.uint64(1)
    factor, width = 0x9E3779B97F4A7C15, 1
    while width < GRAM:
        nxt = h[:-width] * np.uint64(factor)
        nxt += h[width:]
        h, factor, width = nxt, factor * factor % (1 << 64), width * 2
    return mix64(h)


def anchor_runs(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, min_len: int):
    """Runs of windows with one anchor: (first position, number of windows, anchor hash, its place).

    `starts` and `ends` bound the documents in `data`; a window lies within one document.
    """
    n = len(data)
    none = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.int64)
    if n < min_len:
        return none
    grams = _gram_hashes(data)
    key = (grams & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(grams), dtype=np.uint64)
    span, width = min_len - GRAM + 1, 1
    while width * 2 <= span:
        key = np.minimum(key[:-width], key[width:])
        width *= 2
    if width < span:
        key = np.minimum(key[: len(key) - (span - width)], key[span - width :])
    where = (key & np.uint64(0xFFFFFFFF)).astype(np.int64)
    m = len(where)  # == n - min_len + 1
    valid = np.zeros(m + 1, dtype=np.int32)
    long_enough = ends - starts >= min_len
    np.add.at(valid, starts[long_enough], 1)
    np.add.at(valid, ends[long_enough] - min_len + 1, -1)
    valid = np.cumsum(valid[:-1]) > 0
    change = np.ones(m, dtype=bool)
    change[1:] = where[1:] != where[:-1]
    change[starts[starts < m]] = True
    change[1:] |= ~valid[:-1]
    first = np.flatnonzero(change & valid)
    if not len(first):
        return none
    edges = np.append(np.flatnonzero(change | ~valid), m)
    until = edges[np.searchsorted(edges, first, side="right")]
    return first, until - first, grams[where[first]], where[first]


def side_grams(hasher: SpanHasher, place: np.ndarray, low: np.ndarray, high: np.ndarray, min_len: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the anchor with the bytes before, and after, it; 0 where the document ends sooner.

    A window that starts o bytes before the anchor's gram has min_len - GRAM - o bytes after it.
    """
    room = min_len - GRAM
    before, after = (room + 1) // 2, room - (room + 1) // 2 + 1
    out = []
    for start, end in ((place - before, place + GRAM), (place, place + GRAM + after)):
        fits = (start >= low) & (end <= high)
        h = np.zeros(len(place), dtype=np.uint64)
        h[fits] = np.maximum(hasher(start[fits], end[fits]), np.uint64(4))
        out.append(h)
    out[1] ^= np.uint64(2) * (out[1] > 0)  # the two sides are different names
    return out[0], out[1]


def _packed(hashes: np.ndarray) -> bytes:
    """Upper 40 bits of each hash; the bucket's number holds lower ones."""
    return np.ascontiguousarray((hashes >> np.uint64(24)).view(np.uint8).reshape(-1, 8)[:, :5]).tobytes()


def _unpacked(data: bytes) -> np.ndarray:
    wide = np.zeros((len(data) // 5, 8), dtype=np.uint8)
    wide[:, :5] = np.frombuffer(data, dtype=np.uint8).reshape(-1, 5)
    return wide.view(np.uint64).ravel()


def _names(hashes: np.ndarray, buckets: int) -> np.ndarray:
    """What a bucket can tell of a hash: its upper 40 bits and the bucket."""
    return (hashes >> np.uint64(24)) * np.uint64(buckets) + hashes % np.uint64(buckets)


def _batches(ids: list, texts: list):
    """Documents by id, joined to buffers of about BATCH_BYTES: (ids, data, starts, ends)."""
    order = sorted((i for i in range(len(ids)) if ids[i] is not None), key=lambda i: (ids[i], texts[i]))
    at = 0
    while at < len(order):
        size, stop = 0, at
        while stop < len(order) and (stop == at or size + len(texts[order[stop]]) <= BATCH_BYTES):
            size += len(texts[order[stop]])
            stop += 1
        chosen = order[at:stop]
        lens = np.array([len(texts[i]) for i in chosen], dtype=np.int64)
        ends = np.cumsum(lens)
        data = np.frombuffer(b"".join([texts[i] for i in chosen]), dtype=np.uint8)
        yield chosen, np.array([ids[i] for i in chosen], dtype=np.int64), data, ends - lens, ends
        at = stop


def _documents(table: pa.Table) -> tuple[list, list]:
    return table.column("doc_id").to_pylist(), [x or b"" for x in table.column("body").to_pylist()]


def _split(values: np.ndarray, buckets: int):
    """Positions of each bucket that occurs: (bucket, indices)."""
    of = (values % np.uint64(buckets)).astype(np.int64)
    order = np.argsort(of, kind="stable")
    cuts = np.flatnonzero(np.diff(of[order])) + 1
    for part in np.split(order, cuts):
        if len(part):
            yield int(of[part[0]]), part


def _block_anchors(buckets: int, min_len: int):
    def run(table: pa.Table) -> pa.Table:
        block, found = table.column("block")[0].as_py(), []
        for _, _, data, starts, ends in _batches(*_documents(table)):
            first, _, _, place = anchor_runs(data, starts, ends, min_len)
            if len(first):
                owner = np.searchsorted(ends, first, side="right")
                found.append(distinct(np.concatenate(side_grams(SpanHasher(data), place, starts[owner], ends[owner], min_len))))
        every = distinct(np.concatenate(found)) if found else np.zeros(0, np.uint64)
        every = every[every > 0]
        rows = [(b, block, _packed(every[i])) for b, i in _split(every, buckets)]
        return pa.table({"bucket": pa.array([r[0] for r in rows], pa.int64()), "block": pa.array([r[1] for r in rows], pa.int64()), "anchors": pa.array([r[2] for r in rows], pa.binary())})

    return run


def _shared_anchors(buckets: int):
    def run(table: pa.Table) -> pa.Table:
        """Grams that at least two blocks hold, for each of these blocks."""
        blocks = table.column("block").to_pylist()
        bucket = np.uint64(table.column("bucket")[0].as_py())
        lists = [distinct(_unpacked(x)) for x in table.column("anchors").to_pylist()]
        every = np.sort(np.concatenate(lists))
        twice = distinct(every[1:][every[1:] == every[:-1]])
        out_block, out = [], []
        for block, own in zip(blocks, lists, strict=True):
            hit = own[member(own, twice)]
            if len(hit):
                out_block.append(block)
                out.append((hit * np.uint64(buckets) + bucket).tobytes())
        return pa.table({"block": pa.array(out_block, pa.int64()), "anchors": pa.array(out, pa.binary())})

    return run


def _block_runs(table: pa.Table, min_len: int):
    """All runs of a block, batch by batch, with fingerprints of their segments."""
    for chosen, ids, data, starts, ends in _batches(*_documents(table)):
        first, windows, anchor, place = anchor_runs(data, starts, ends, min_len)
        if not len(first):
            continue
        hasher = SpanHasher(data)
        print_ = hasher(first, first + windows + (min_len - 1)) ^ anchor
        owner = np.searchsorted(ends, first, side="right")
        yield chosen, ids, data, starts, ends, first, windows, anchor, print_, owner, place, hasher


def _block_segments(buckets: int, min_len: int):
    def run(docs: pa.Table, shared: pa.Table) -> pa.Table:
        cols: dict[str, list] = {k: [] for k in ("bucket", "block", "prints", "anchors", "docs", "windows", "bytes")}
        names = [np.frombuffer(x, dtype=np.uint64) for x in shared.column("anchors").to_pylist()]
        known = distinct(np.concatenate(names)) if names else np.zeros(0, np.uint64)
        if docs.num_rows:
            block = docs.column("block")[0].as_py()

            def sides(starts, ends, owner, place, hasher):
                return side_grams(hasher, place, starts[owner], ends[owner], min_len)

            # grams of two documents of this very block count too
            own = []
            for _, own_ids, _, starts, ends, _, _, _, _, owner, place, hasher in _block_runs(docs, min_len):
                for side in sides(starts, ends, owner, place, hasher):
                    own.append((side, own_ids[owner]))
            if own:
                gram, ids = np.concatenate([x[0] for x in own]), np.concatenate([x[1] for x in own])
                order = np.argsort(gram, kind="stable")
                gram, ids = gram[order], ids[order]
                differ = (gram[1:] == gram[:-1]) & (ids[1:] != ids[:-1]) & (gram[1:] > 0)
                known = distinct(np.concatenate([known, _names(gram[1:][differ], buckets)]))
            seen: set[int] = set()
            parts: list[tuple] = []
            for _, ids, data, starts, ends, first, windows, anchor, print_, owner, place, hasher in _block_runs(docs, min_len):
                wanted = np.zeros(len(first), dtype=bool)
                for side in sides(starts, ends, owner, place, hasher):
                    wanted |= member(_names(side, buckets), known) & (side > 0)
                keep = np.flatnonzero(wanted)
                raw = data.tobytes()
                for i, p in zip(keep.tolist(), print_[keep].tolist(), strict=True):
                    if p not in seen:  # documents come by id, so the first owner is the least
                        seen.add(p)
                        a = int(first[i])
                        parts.append((p, int(anchor[i]), int(ids[owner[i]]), int(windows[i]), raw[a : a + int(windows[i]) + min_len - 1]))
            if parts:
                anchors = np.array([p[1] for p in parts], dtype=np.uint64)
                for b, part in _split(anchors, buckets):
                    rows = [parts[i] for i in part.tolist()]
                    cols["bucket"].append(b)
                    cols["block"].append(block)
                    cols["prints"].append(np.array([r[0] for r in rows], dtype=np.uint64).tobytes())
                    cols["anchors"].append(anchors[part].tobytes())
                    cols["docs"].append(np.array([r[2] for r in rows], dtype=np.int64).tobytes())
                    cols["windows"].append(np.array([r[3] for r in rows], dtype=np.uint16).tobytes())
                    cols["bytes"].append(zstandard.ZstdCompressor(level=1).compress(b"".join([r[4] for r in rows])))
        return pa.table({k: pa.array(v, pa.int64() if k in ("bucket", "block") else pa.binary()) for k, v in cols.items()})

    return run


def bounded_order(text: np.ndarray, depth: int) -> np.ndarray:
    """Suffix positions sorted by their first `depth` bytes (a power of two, 8 at least)."""
    n = len(text)
    padded = np.concatenate([text, np.full(depth, SEP, np.uint8)])
    key, width = padded.astype(np.uint64), 1
    while width < 8:
        key = (key[:-width] << np.uint64(8 * width)) | key[width:]
        width *= 2
    key = key[:n]
    while True:
        order = np.argsort(key, kind="stable" if width >= depth else None)
        if width >= depth:
            return order
        rank = np.empty(n + depth, dtype=np.uint64)
        ranked = key[order]
        rank[order] = np.concatenate([[0], np.cumsum(ranked[1:] != ranked[:-1])]).astype(np.uint64)
        rank[n:] = n
        key = rank[:n] * np.uint64(n + 1) + rank[width : n + width]
        width *= 2


def common_prefix_bounds(bwt: np.ndarray, limit: int) -> np.ndarray:
    """Shared prefix of each suffix with its predecessor where below `limit`, else -1.

    `bwt` is the transform in suffix order.  The queue of level l holds the intervals of strings
    of l bytes whose right edge was settled one level earlier.  Each is extended to the left by
    every byte in it; an edge of the extension that nobody has settled shares exactly l bytes.
    """
    n = len(bwt)
    by_byte = np.argsort(bwt, kind="stable").astype(np.int32)
    to = np.empty(n, dtype=np.int32)
    to[by_byte] = np.arange(n, dtype=np.int32)
    sorted_bytes = bwt[by_byte]
    same = sorted_bytes[1:] == sorted_bytes[:-1]
    following = np.full(n, n, dtype=np.int32)
    following[by_byte[:-1][same]] = by_byte[1:][same]
    previous = np.full(n, -1, dtype=np.int32)
    previous[by_byte[1:][same]] = by_byte[:-1][same]
    usable = bwt != SEP
    settled = np.full(n + 1, -1, dtype=np.int16)
    settled[0] = settled[n] = 0
    left, right = np.array([0], dtype=np.int32), np.array([n], dtype=np.int32)
    for level in range(limit):
        sizes = right - left
        total = int(sizes.sum())
        if not total:
            break
        at = np.arange(total, dtype=np.int32)
        at += np.repeat(left - (np.cumsum(sizes) - sizes).astype(np.int32), sizes)
        ok = usable[at]
        last = at[ok & (following[at] >= np.repeat(right, sizes))]
        head = at[ok & (previous[at] < np.repeat(left, sizes))]
        # intervals of one level are disjoint, so heads and tails pair up in sorted order
        new_right, new_left = np.sort(to[last]) + 1, np.sort(to[head])
        fresh = settled[new_right] < 0
        if level == 0:
            fresh |= new_right == n
        left, right = new_left[fresh], new_right[fresh]
        settled[right] = level
    return settled


def repeat_minima(text: np.ndarray, owner: np.ndarray, min_len: int) -> np.ndarray:
    """Least owner among all positions that start the same `min_len` bytes, for each position."""
    depth = 8
    while depth <= min_len:
        depth *= 2
    order = bounded_order(text, depth)
    before = order - 1
    bwt = text[before]
    bwt[before < 0] = SEP
    bounds = common_prefix_bounds(bwt, min_len)
    heads = np.flatnonzero(bounds[:-1] >= 0)
    least = np.minimum.reduceat(owner[order], heads)
    out = np.empty(len(text), dtype=np.int64)
    out[order] = np.repeat(least, np.diff(np.append(heads, len(text))))
    return out


def _bucket_minima(min_len: int):
    tail = min_len - 1

    def run(table: pa.Table) -> pa.Table:
        bin_ = lambda name, kind: [np.frombuffer(x, dtype=kind) for x in table.column(name).to_pylist()]
        prints, anchors, owners, windows = bin_("prints", np.uint64), bin_("anchors", np.uint64), bin_("docs", np.int64), bin_("windows", np.uint16)
        blobs = [zstandard.ZstdDecompressor().decompress(x) for x in table.column("bytes").to_pylist()]
        starts = [np.cumsum(w.astype(np.int64) + tail) - (w + tail) for w in windows]
        every = np.concatenate(prints)
        order = np.argsort(every, kind="stable")
        head = np.ones(len(every), dtype=bool)
        head[1:] = every[order[1:]] != every[order[:-1]]
        index = order[head]
        back = np.empty(len(every), dtype=np.int64)
        back[order] = np.cumsum(head) - 1
        source = np.repeat(np.arange(len(blobs)), [len(p) for p in prints])[index]
        least = np.full(len(index), _NO_DOC, dtype=np.int64)
        np.minimum.at(least, back, np.concatenate(owners))
        start, width, anchor = (np.concatenate(x)[index] for x in (starts, [w.astype(np.int64) for w in windows], anchors))
        by_anchor = np.argsort(anchor, kind="stable")
        sizes = width[by_anchor] + tail + 1
        # whole anchors together, in indexes of a bounded size
        breaks = np.flatnonzero(np.diff(anchor[by_anchor])) + 1
        cuts, filled, at = [], 0, 0
        for stop in np.append(breaks, len(by_anchor)).tolist():
            size = int(sizes[at:stop].sum())
            if filled and filled + size > INDEX_BYTES:
                cuts.append(at)
                filled = 0
            filled, at = filled + size, stop
        counts = np.zeros(len(index), dtype=np.int64)
        offsets = np.zeros(len(index), dtype=np.int64)
        pieces: list[tuple] = []
        done = 0
        for chunk in np.split(by_anchor, cuts):
            text = np.frombuffer(b"".join([blobs[s][a : a + w + tail] + b"\xff" for s, a, w in zip(source[chunk].tolist(), start[chunk].tolist(), width[chunk].tolist(), strict=True)]), dtype=np.uint8)
            lens = width[chunk] + tail + 1
            begin = np.cumsum(lens) - lens
            minima = repeat_minima(text, np.repeat(least[chunk], lens), min_len)
            w = width[chunk]
            base = np.cumsum(w) - w
            place = np.arange(int(w.sum())) - np.repeat(base, w)
            value = minima[np.repeat(begin, w) + place]
            cut = np.ones(len(value), dtype=bool)
            cut[1:] = (value[1:] != value[:-1]) | (place[1:] == 0)
            head = np.flatnonzero(cut)
            length = np.diff(np.append(head, len(value)))
            seg = np.searchsorted(base, head, side="right") - 1
            counts[chunk] = np.bincount(seg, minlength=len(chunk))
            offsets[chunk] = done + np.cumsum(counts[chunk]) - counts[chunk]
            done += len(head)
            pieces.append((place[head], length, value[head]))
        at, length, value = (np.concatenate([p[i] for p in pieces]) for i in range(3))
        out: dict[str, list] = {k: [] for k in ("block", "prints", "counts", "at", "lengths", "least")}
        pos = 0
        for block, own in zip(table.column("block").to_pylist(), prints, strict=True):
            d = back[pos : pos + len(own)]
            pos += len(own)
            n = counts[d]
            pick = np.repeat(offsets[d] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            out["block"].append(block)
            for name, x, kind in (("prints", own, np.uint64), ("counts", n, np.uint16), ("at", at[pick], np.uint16), ("lengths", length[pick], np.uint16), ("least", value[pick], np.int64)):
                out[name].append(x.astype(kind).tobytes())
        return pa.table({k: pa.array(v, pa.int64() if k == "block" else pa.binary()) for k, v in out.items()})

    return run


def _block_spans(min_len: int):
    def run(docs: pa.Table, minima: pa.Table) -> pa.Table:
        ids, texts = _documents(docs)
        spans: list[list] = [[] for _ in ids]
        kept = list(texts)
        if minima.num_rows:
            join = lambda name, kind: np.concatenate([np.frombuffer(x, dtype=kind) for x in minima.column(name).to_pylist()])
            prints, counts, at, lengths, least = join("prints", np.uint64), join("counts", np.uint16).astype(np.int64), join("at", np.uint16), join("lengths", np.uint16), join("least", np.int64)
            offset = np.cumsum(counts) - counts
            order = np.argsort(prints)
            ordered = prints[order]
            for chosen, own, data, starts, ends, first, _, _, print_, owner, _, _ in _block_runs(docs, min_len):
                slot = np.minimum(np.searchsorted(ordered, print_), len(ordered) - 1)
                hit = np.flatnonzero(ordered[slot] == print_)
                entry = order[slot[hit]]
                n = counts[entry]
                pick = np.repeat(offset[entry] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
                run_of = np.repeat(hit, n)
                older = least[pick] < own[owner[run_of]]
                begin = first[run_of[older]] + at[pick[older]]
                edge = np.zeros(len(data) + 1, dtype=np.int32)
                np.add.at(edge, begin, 1)
                np.add.at(edge, begin + lengths[pick[older]] + (min_len - 1), -1)
                gone = np.cumsum(edge[:-1]) > 0
                for j in np.unique(owner[run_of[older]]).tolist():
                    a, b = int(starts[j]), int(ends[j])
                    mask = gone[a:b]
                    flips = np.flatnonzero(np.diff(np.concatenate([[False], mask, [False]]).astype(np.int8)))
                    spans[chosen[j]] = [{"start": s, "end": e} for s, e in zip(flips[::2].tolist(), flips[1::2].tolist(), strict=True)]
                    kept[chosen[j]] = data[a:b][~mask].tobytes()
        return pa.table({"doc_id": pa.array(ids, pa.int64()), "n_bytes": pa.array([len(t) for t in texts], pa.int64()), "spans": pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), "kept": pa.array(kept, pa.binary())})

    return run


def remove_repeats(docs: DataFrame, min_len: int = MIN_LEN, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """doc_id, n_bytes, spans (removed byte ranges, maximal) and kept (the other bytes)."""
    if min_len < GRAM + 8:
        raise ValueError(f"min_len must be at least {GRAM + 8}")
    blocks = parts_for(text_bytes(docs), block_bytes)
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.encode("text", "UTF-8").alias("body"))
    own = own.select("doc_id", "body", F.pmod(F.xxhash64("doc_id", "body"), F.lit(blocks)).alias("block"))
    by_block = own.groupBy("block")
    shared = by_block.applyInArrow(_block_anchors(blocks, min_len), "bucket long, block long, anchors binary").groupBy("bucket").applyInArrow(_shared_anchors(blocks), "block long, anchors binary")
    segments = by_block.cogroup(shared.groupBy("block")).applyInArrow(_block_segments(blocks, min_len), "bucket long, block long, prints binary, anchors binary, docs binary, windows binary, bytes binary")
    minima = segments.groupBy("bucket").applyInArrow(_bucket_minima(min_len), "block long, prints binary, counts binary, at binary, lengths binary, least binary")
    return by_block.cogroup(minima.groupBy("block")).applyInArrow(_block_spans(min_len), "doc_id long, n_bytes long, spans array<struct<start:long,end:long>>, kept binary")
