"""Removal of repeated passages with an enhanced suffix array and its common-prefix interval tree.

A byte goes if a string of ``least`` bytes that covers it also starts earlier (smaller id, or same document and earlier start). Equivalently:
of every maximal repeat (a string of that length or more whose occurrences cannot all be extended by the same byte, left or right), all
occurrences but the first go. Maximal repeats are the left-diverse nodes of the interval tree of a suffix array.

One suffix array over a corpus does not fit any machine, so the corpus is first cut by content. Every window of ``least`` bytes names the
k-gram of smallest hash inside it (its anchor), which depends on nothing but the window, so equal windows name equal anchors at equal
places. Consecutive windows with one anchor form a unit of about ``(least - k) / 2`` windows. Then

1. units meet by anchor (packed, a row per batch and bucket). Units equal as a whole (anchor, length and 160 bits of three hashes) are settled: all but
   the first go. A batch settles its own first, so a passage in many documents is sent once per batch.
2. Anchors found with different surroundings leave one unit for each surrounding. Their bytes are fetched from the documents, meet by anchor
   again, and a suffix array with its interval tree settles them exactly: what goes is what left-diverse intervals report.
3. The spans of a document are gathered and cut out.

Buckets number with the size of the input, so each holds a few megabytes; an anchor with very many different surroundings stays in one bucket, with
some 30 bytes for each in step 1 and 130 in step 2.

Defined cases: null text counts as empty; texts shorter than ``least`` lose nothing; matches never cross documents; a row that repeats an id with the same
text is the same document given twice (both rows get its result); ids must otherwise be unique; rows with a null id are neither compared nor cut; an empty table gives no rows;
very long texts are taken whole and other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import parts_for, text_of, written
from .near_dup import _INVERSE, _PRIME, _powers, mixed

CHUNK = 1 << 20
_SECOND_PRIME = np.uint64(0xD6E8FEB86659FD93)
_SECOND_INVERSE = np.uint64(pow(0xD6E8FEB86659FD93, -1, 1 << 64))
#: Other values for the bytes in the second hash of a unit.
SECOND = mixed(np.arange(1, 257, dtype=np.uint64))


# ---- the suffix array and its interval tree


def suffix_ranks(data: np.ndarray, bounds: np.ndarray) -> tuple[list[tuple[int, np.ndarray]], np.ndarray]:
    """([(length, rank of every position among prefixes of that length)], bytes left in its text); texts end with a byte below all others.

    Prefix doubling from 8 bytes on; it stops once all suffixes of the longest text are told apart or covered.
    """
    n = len(data)
    ends = np.repeat(bounds[1:], np.diff(bounds))
    left = ends - np.arange(n)
    word = np.zeros(n, np.uint64)
    for k in range(8):
        byte = np.zeros(n, np.uint64)
        byte[: max(n - k, 0)] = data[k:]
        byte[left <= k] = 0
        word = (word << np.uint64(8)) | byte
    _, rank = np.unique(word, return_inverse=True)
    length, levels = 8, [(8, rank)]
    longest = int(np.diff(bounds).max()) if len(bounds) > 1 else 0
    while length < longest and rank.max(initial=0) + 1 < n:
        second = np.zeros(n, np.int64)
        second[: max(n - length, 0)] = rank[length:] + 1
        second[left <= length] = 0
        _, rank = np.unique(rank.astype(np.int64) * (n + 1) + second, return_inverse=True)
        length *= 2
        levels.append((length, rank))
    return levels, left


def common_prefixes(a: np.ndarray, b: np.ndarray, data: np.ndarray, levels, left: np.ndarray) -> np.ndarray:
    """Length of the common prefix of suffixes a[i] and b[i], within their texts."""
    n = len(data)
    out, cap = np.zeros(len(a), np.int64), np.minimum(left[a], left[b])
    while True:
        before = out.copy()
        for length, rank in reversed(levels):
            go = np.flatnonzero(out < cap)
            same = rank[np.minimum(a[go] + out[go], n - 1)] == rank[np.minimum(b[go] + out[go], n - 1)]
            out[go[same]] += length
        if (out == before).all() or (out >= cap).all():
            break
    for _ in range(8):
        go = np.flatnonzero(out < cap)
        out[go] += data[np.minimum(a[go] + out[go], n - 1)] == data[np.minimum(b[go] + out[go], n - 1)]
        if not len(go):
            break
    return np.minimum(out, cap)


def enhanced_suffix_array(data: np.ndarray, bounds: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
    """(suffixes of at least ``least`` bytes in order, common prefix of each with the one before)."""
    levels, left = suffix_ranks(data, bounds)
    starts = np.flatnonzero(left >= least)
    order = starts[np.lexsort((-left[starts], levels[-1][1][starts]))]
    lcp = np.zeros(len(order), np.int64)
    if len(order) > 1:
        lcp[1:] = common_prefixes(order[:-1], order[1:], data, levels, left)
    return order, lcp


def repeat_intervals(order: np.ndarray, lcp: np.ndarray, before: np.ndarray, least: int) -> Iterator[tuple[int, int, int, list[int], bool]]:
    """(length, first, last, starts of its child intervals, left-diverse?) of each interval of the suffix array, children before parents.

    A stack holds the open intervals; each carries the byte before its suffixes while that is the same for all, else -1 (diverse).
    ``before``: the byte before each position, a different negative number at each text's start.
    """
    values, lefts, n = lcp.tolist(), before[order].tolist(), len(order)
    stack: list[list] = []  # length, first, byte before or -1, child starts
    for i in range(1, n + 1):
        depth = values[i] if i < n else 0
        if depth < least:
            depth = 0
        first, byte = i - 1, lefts[i - 1]
        child = first
        while stack and stack[-1][0] > depth:
            length, first, own, children = stack.pop()
            if children[-1] != child:
                children.append(child)
            own = own if own == byte else -1
            yield length, first, i - 1, children, own == -1
            child, byte = first, own
        if depth:
            if stack and stack[-1][0] == depth:
                top = stack[-1]
                if top[3][-1] != child:
                    top[3].append(child)
                if top[2] != byte:
                    top[2] = -1
            else:
                stack.append([depth, first, byte, [child]])


def maximal_repeats(texts: list[bytes], least: int) -> list[tuple[bytes, list[tuple[int, int]]]]:
    """All maximal repeats of at least ``least`` bytes, each with every occurrence as (text number, start)."""
    data, bounds, before = _joined(texts)
    if not len(data):
        return []
    order, lcp = enhanced_suffix_array(data, bounds, least)
    out = []
    for length, lo, hi, _, diverse in repeat_intervals(order, lcp, before, least):
        if not diverse:
            continue
        at = np.sort(order[lo : hi + 1])
        which = np.searchsorted(bounds, at, "right") - 1
        out.append((data[at[0] : at[0] + length].tobytes(), list(zip(which.tolist(), (at - bounds[which]).tolist(), strict=True))))
    return out


def _joined(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    data = np.frombuffer(b"".join(texts), np.uint8)
    bounds = np.concatenate([[0], np.cumsum([len(t) for t in texts], dtype=np.int64)]).astype(np.int64)
    before = np.empty(len(data), np.int64)
    before[1:] = data[:-1]
    starts = bounds[:-1][np.diff(bounds) > 0]
    before[starts] = -2 - np.arange(len(starts))
    return data, bounds, before


def later_occurrences(texts: list[bytes], place: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text number, start, length) of occurrences that are not the first of their maximal repeat; they cover all such occurrences.

    ``place``: a number for the start of each text; position p of text t comes at place[t] + p, ties of one place being one position given twice.
    In each interval only the smallest position of a child can be new to it, so every suffix is settled once: linear in the suffixes, whatever the nesting.
    Left-diverse intervals report what they settle. One that is not left-diverse reports nothing: the same occurrences, a byte longer to the left, are an
    interval too, and the leftmost of these is a maximal repeat that covers them.
    """
    data, bounds, before = _joined(texts)
    order, lcp = enhanced_suffix_array(data, bounds, least)
    which = np.searchsorted(bounds, order, "right") - 1
    places = (place[which] + (order - bounds[which])).tolist()
    smallest: dict[int, int] = {}  # interval start -> index of its smallest suffix
    hits, lengths = [], []
    for length, _, _, children, diverse in repeat_intervals(order, lcp, before, least):
        heads = [smallest.get(c, c) for c in children]
        best = min(heads, key=places.__getitem__)
        if diverse:
            later = [h for h in heads if places[h] != places[best]]
            hits += later
            lengths += [length] * len(later)
        smallest[children[0]] = best
    hit = np.array(hits, np.int64)
    at = order[hit] if len(hit) else hit
    own = which[hit] if len(hit) else hit
    return own, at - bounds[own], np.array(lengths, np.int64)


# ---- units


def units_of(data: np.ndarray, bounds: np.ndarray, least: int, k: int) -> tuple[np.ndarray, ...]:
    """(text number, start, windows, anchor hash, unit hash, second unit hash) of every unit of the concatenated texts.

    A window's anchor is the k-gram whose hash has the smallest upper half, the leftmost of several: a rule on the window's bytes alone.
    """
    n, width = len(data), least - k + 1
    if n < least:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.uint64, np.uint64, np.uint32))
    inverse = _powers(n, _INVERSE)
    sums = np.zeros(n + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * _powers(n, _PRIME), out=sums[1:])
    grams = mixed((sums[k:] - sums[:-k]) * inverse[: n - k + 1])
    half = np.uint64(32)
    low = ((grams >> half) << half) | np.arange(len(grams), dtype=np.uint64)
    span = 1
    while span * 2 <= width:  # sliding minimum by doubling; the position in the low bits makes the leftmost win
        low = np.minimum(low[:-span], low[span:])
        span *= 2
    if width > span:
        low = np.minimum(low[: len(low) - (width - span)], low[width - span :])
    anchor = (low & np.uint64((1 << 32) - 1)).astype(np.int64)
    windows = len(anchor)
    text = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    inside = text[:windows] == text[least - 1 : least - 1 + windows]
    new = inside.copy()
    new[1:] &= (anchor[1:] != anchor[:-1]) | ~inside[:-1] | (text[1:windows] != text[: windows - 1])
    start = np.flatnonzero(new)
    stop = inside.copy()
    stop[:-1] &= new[1:] | ~inside[1:]
    end = np.flatnonzero(stop) + 1
    count = end - start
    place = mixed((anchor[start] - start).astype(np.uint64) << np.uint64(32) | count.astype(np.uint64))
    whole = mixed(((sums[end + least - 1] - sums[start]) * inverse[start]) + place)
    np.cumsum(SECOND[data] * _powers(n, _SECOND_PRIME), out=sums[1:])
    check = mixed((sums[end + least - 1] - sums[start]) * _powers(n, _SECOND_INVERSE)[start] + place) >> np.uint64(32)
    return text[start], start - bounds[text[start]], count, grams[anchor[start]], whole, check.astype(np.uint32)


def _settle(doc: np.ndarray, start: np.ndarray, unit: np.ndarray, check: np.ndarray, anchor: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(indices in the order anchor, unit, document, start; index of the first of its unit for each of them).

    Units count as equal when the 64 bits of their anchor's hash, the 64 of their own and 32 of a second one with other factors and other values for the bytes agree.
    """
    order = np.lexsort((start, doc, check, unit, anchor))
    new = np.ones(len(order), bool)
    new[1:] = (anchor[order[1:]] != anchor[order[:-1]]) | (unit[order[1:]] != unit[order[:-1]]) | (check[order[1:]] != check[order[:-1]])
    return order, order[np.flatnonzero(new)[np.cumsum(new) - 1]] if len(order) else order


_SPAN = np.dtype([("doc", "<i8"), ("start", "<u4"), ("n", "<u4")])
_UNIT = [("anchor", "<u8"), ("unit", "<u8"), ("check", "<u4"), ("doc", "<i8"), ("start", "<u4"), ("n", "<u2")]


def _pack_units(columns: dict[str, np.ndarray]) -> bytes:
    """Column by column, ids as differences: what compresses, does."""
    doc = columns["doc"].astype(np.int64)
    parts = {**columns, "doc": np.diff(doc, prepend=np.int64(0))}
    return b"".join(parts[name].astype(kind).tobytes() for name, kind in _UNIT)


def _unpack_units(data: bytes) -> dict[str, np.ndarray]:
    size = sum(np.dtype(kind).itemsize for _, kind in _UNIT)
    n, at, out = len(data) // size, 0, {}
    for name, kind in _UNIT:
        out[name] = np.frombuffer(data, kind, n, at)
        at += n * np.dtype(kind).itemsize
    out["doc"] = np.cumsum(out["doc"])
    return out


def _by_doc(doc: np.ndarray, values: np.ndarray) -> Iterator[tuple[int, bytes]]:
    if not len(doc):
        return
    order = np.argsort(doc, kind="stable")
    doc, values = doc[order], values[order]
    cuts = np.flatnonzero(np.diff(doc, prepend=doc[:1] - 1))
    for lo, hi in zip(cuts, [*cuts[1:], len(doc)], strict=True):
        yield int(doc[lo]), values[lo:hi].tobytes()


def _long_binary(batch: pa.RecordBatch, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a text column."""
    texts = batch.column(k).cast(pa.large_binary())
    _, offsets, data = texts.buffers()
    at = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + len(texts) + 1]
    return (np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)), at


def _unit_rows(docs: DataFrame, least: int, k: int, buckets: int) -> DataFrame:
    """bucket, units, covered: the units of a batch by bucket, those already settled as spans of their documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = np.asarray(batch.column(0))
            data, at = _long_binary(batch, 1)
            found, t = [], 0
            while t < len(ids):
                to = min(len(ids), max(t + 1, int(np.searchsorted(at, at[t] + CHUNK, "right")) - 1))
                text, *rest = units_of(data[at[t] : at[to]], at[t : to + 1] - at[t], least, k)
                found.append((ids[t + text], *rest))
                t = to
            doc, start, count, anchor, unit, check = (np.concatenate(x) for x in zip(*found, strict=True)) if found else [np.zeros(0, np.uint64)] * 6
            order, first = _settle(doc, start, unit, check, anchor)
            settled = (doc[order] != doc[first]) | (start[order] != start[first])
            spans = np.zeros(int(settled.sum()), _SPAN)
            gone = order[settled]
            spans["doc"], spans["start"], spans["n"] = doc[gone], start[gone], count[gone] + least - 1
            keep = np.sort(order[~settled])
            bucket = (anchor[keep] % np.uint64(buckets)).astype(np.int64)
            by = np.lexsort((start[keep], doc[keep], bucket))
            keep, bucket = keep[by], bucket[by]
            cuts = np.searchsorted(bucket, np.arange(buckets + 1))
            numbers, blobs, covered = [], [], []
            for b in np.unique(bucket):
                own = keep[cuts[b] : cuts[b + 1]]
                numbers.append(int(b))
                blobs.append(_pack_units({"anchor": anchor[own], "unit": unit[own], "check": check[own], "doc": doc[own], "start": start[own], "n": count[own]}))
                covered.append(None)
            if len(spans):
                numbers.append(int(ids[0]) % buckets)
                blobs.append(None)
                covered.append(spans.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(numbers, pa.int32()), pa.array(blobs, pa.binary()), pa.array(covered, pa.binary())], ["bucket", "units", "covered"])

    return docs.mapInArrow(run, "bucket int, units binary, covered binary")


def _settled_rows(rows: DataFrame, least: int) -> DataFrame:
    """doc_id, covered (start, length pairs), wanted (start, windows, anchor of units that need their bytes)."""
    wanted_type = np.dtype([("start", "<u4"), ("n", "<u4"), ("anchor", "<u8")])

    def out(doc: list[int], covered: list, wanted: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(covered, pa.binary()), pa.array(wanted, pa.binary())], ["doc_id", "covered", "wanted"])

    def spans(doc: np.ndarray, start: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
        pairs = np.stack([start, n], 1).astype("<u4")
        found = list(_by_doc(doc, pairs))
        return out([d for d, _ in found], [x for _, x in found], [None] * len(found))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blobs = []
        for batch in batches:
            for units, covered in zip(batch.column(1), batch.column(2), strict=True):
                if covered.is_valid:
                    x = np.frombuffer(covered.as_py(), _SPAN)
                    yield spans(x["doc"], x["start"], x["n"])
                if units.is_valid:
                    blobs.append(_unpack_units(units.as_py()))
        if not blobs:
            return
        anchor = np.concatenate([b["anchor"] for b in blobs])
        order = np.argsort(anchor)
        same = np.zeros(len(order) + 1, bool)
        same[1:-1] = anchor[order[1:]] == anchor[order[:-1]]
        again = np.sort(order[same[1:] | same[:-1]])  # units whose anchor is found twice
        anchor = anchor[again]
        unit, check, doc, start, n = (np.concatenate([b[c] for b in blobs])[again] for c in ("unit", "check", "doc", "start", "n"))
        del blobs, order, same
        order, first = _settle(doc, start, unit, check, anchor)
        later = (doc[order] != doc[first]) | (start[order] != start[first])
        gone = order[later]
        yield spans(doc[gone], start[gone], n[gone].astype(np.int64) + least - 1)
        heads = np.unique(first)
        _, which, count = np.unique(anchor[heads], return_inverse=True, return_counts=True)
        heads = heads[count[which] > 1]
        wanted = np.zeros(len(heads), wanted_type)
        wanted["start"], wanted["n"], wanted["anchor"] = start[heads], n[heads], anchor[heads]
        found = list(_by_doc(doc[heads], wanted))
        yield out([d for d, _ in found], [None] * len(found), [x for _, x in found])

    return rows.mapInArrow(run, "doc_id long, covered binary, wanted binary")


def _fetched(docs: DataFrame, wanted: DataFrame, least: int, buckets: int) -> DataFrame:
    """bucket, blob of (anchor, document, start, bytes) of the wanted units."""
    wanted_type = np.dtype([("start", "<u4"), ("n", "<u4"), ("anchor", "<u8")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            by: dict[int, tuple[list, list, list]] = {}
            for doc, text, blobs in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.large_binary()), batch.column(2), strict=True):
                whole = memoryview(text.as_buffer())
                for w in np.unique(np.concatenate([np.frombuffer(b, wanted_type) for b in blobs.as_py()])).tolist():
                    docs_of, starts, texts = by.setdefault(w[2] % buckets, ([], [], []))
                    docs_of.append(doc)
                    starts.append(w[0])
                    texts.append(whole[w[0] : w[0] + w[1] + least - 1].tobytes())
            if by:
                rows = list(by.items())
                yield pa.RecordBatch.from_arrays(
                    [pa.array([b for b, _ in rows], pa.int32()), pa.array([x[0] for _, x in rows], pa.list_(pa.int64())), pa.array([x[1] for _, x in rows], pa.list_(pa.int64())), pa.array([x[2] for _, x in rows], pa.list_(pa.binary()))],
                    ["bucket", "docs", "starts", "texts"],
                )

    joined = docs.join(wanted, "doc_id").select("doc_id", "text", "wanted")
    return joined.mapInArrow(run, "bucket int, docs array<long>, starts array<long>, texts array<binary>")


def _repeated(texts: list[bytes], least: int) -> np.ndarray:
    """Which texts hold a window whose hash is found twice: the others need no suffix array."""
    data, bounds, _ = _joined(texts)
    n = len(data)
    sums = np.zeros(n + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * _powers(n, _PRIME), out=sums[1:])
    text = np.repeat(np.arange(len(texts)), np.maximum(np.diff(bounds) - least + 1, 0))
    counts = np.maximum(np.diff(bounds) - least + 1, 0)
    at = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts) + np.repeat(bounds[:-1], counts)
    hashes = (sums[at + least] - sums[at]) * _powers(n, _INVERSE)[at]
    order = np.argsort(hashes)
    same = hashes[order[1:]] == hashes[order[:-1]]
    out = np.zeros(len(texts), bool)
    out[text[order[1:][same]]] = True
    out[text[order[:-1][same]]] = True
    return out


def _tree_rows(rows: DataFrame, least: int) -> DataFrame:
    """doc_id, covered: what the interval trees of a bucket's units settle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        doc, start, texts = [], [], []
        for batch in batches:
            for row in batch.to_pylist():
                doc += row["docs"]
                start += row["starts"]
                texts += row["texts"]
        if not texts:
            return
        keep = np.flatnonzero(_repeated(texts, least))
        if not len(keep):
            return
        doc, start, texts = np.array(doc, np.int64)[keep], np.array(start, np.int64)[keep], [texts[k] for k in keep]
        # an order number for documents leaves room for positions
        _, number = np.unique(doc, return_inverse=True)
        own, at, n = later_occurrences(texts, number.astype(np.int64) * (int(start.max()) + 1 + max(map(len, texts))) + start, least)
        found = list(_by_doc(doc[own], np.stack([start[own] + at, n], 1).astype("<u4")))
        yield pa.RecordBatch.from_arrays([pa.array([d for d, _ in found], pa.int64()), pa.array([x for _, x in found], pa.binary())], ["doc_id", "covered"])

    return rows.mapInArrow(run, "doc_id long, covered binary")


def covered_runs(blobs: list[bytes] | None, n: int) -> list[tuple[int, int]]:
    """Maximal runs (start, end) of the union of the packed spans."""
    if not blobs:
        return []
    pairs = np.concatenate([np.frombuffer(b, "<u4").reshape(-1, 2) for b in blobs]).astype(np.int64)
    pairs = pairs[np.argsort(pairs[:, 0], kind="stable")]
    ends = np.maximum.accumulate(pairs[:, 0] + pairs[:, 1])
    new = np.ones(len(pairs), bool)
    new[1:] = pairs[1:, 0] > ends[:-1]
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(pairs)) - 1
    return list(zip(pairs[first, 0].tolist(), np.minimum(ends[last], n).tolist(), strict=True))


def repeated_spans(docs: DataFrame, *, least: int = 100, k: int = 32, bucket_bytes: int = 4 << 20) -> DataFrame:
    """doc_id, covered: arrays of packed (start, length) spans to remove; documents without any are absent. ``docs``: doc_id (long), text."""
    if not 0 < k <= least < 1 << 16:
        raise ValueError("a gram has at most as many bytes as the shortest repeat, which has fewer than 65,536")
    docs = docs.filter("doc_id is not null")
    buckets = parts_for(docs, bucket_bytes)
    rows = _unit_rows(docs, least, k, buckets)
    settled = written(_settled_rows(rows.repartitionById(buckets, F.col("bucket")), least), "units")
    wanted = settled.filter("wanted is not null").select("doc_id", "wanted")
    amount = (wanted.agg(F.sum(F.octet_length("wanted"))).first()[0] or 0) // 16
    wanted = wanted.groupBy("doc_id").agg(F.collect_list("wanted").alias("wanted"))
    trees = max(1, -(-amount // 30_000))
    fetched = _fetched(docs, wanted, least, trees)
    more = _tree_rows(fetched.repartitionById(trees, F.col("bucket")), least)
    spans = settled.filter("covered is not null").select("doc_id", "covered").union(more)
    return spans.groupBy("doc_id").agg(F.collect_list("covered").alias("covered"))


def remove_repeats(docs: DataFrame, *, least: int = 100, k: int = 32, with_rest: bool = False, **options) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_removed, n_spans, kept_sha256; with ``with_rest`` also spans and the remaining bytes."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text"))
    joined = docs.join(repeated_spans(docs, least=least, k=k, **options), "doc_id", "left").select("doc_id", "text", "covered")
    span_type = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for text, blobs in zip(batch.column(1).cast(pa.large_binary()), batch.column(2), strict=True):
                whole = memoryview(text.as_buffer())
                runs = covered_runs(blobs.as_py(), len(whole))
                at, rest = 0, []
                for lo, hi in runs:
                    rest.append(whole[at:lo])
                    at = hi
                rest = b"".join([*rest, whole[at:]])
                rows.append((len(whole), len(whole) - len(rest), len(runs), hashlib.sha256(rest).hexdigest(), [{"start": a, "end": b} for a, b in runs] if with_rest else None, rest if with_rest else None))
            cols = list(zip(*rows, strict=True)) if rows else [()] * 6
            arrays = [batch.column(0)] + [pa.array(c, t) for c, t in zip(cols, [pa.int64()] * 3 + [pa.string(), span_type, pa.binary()], strict=True)]
            names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans", "rest"]
            yield pa.RecordBatch.from_arrays(arrays[: 7 if with_rest else 5], names[: 7 if with_rest else 5])

    return joined.mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", spans array<struct<start:long,end:long>>, rest binary" if with_rest else ""))


ORACLE = r"""
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h, strlen(coalesce(text, ''))::BIGINT AS n FROM documents),
     win AS (SELECT doc_id, i, substr(h, (2 * i + 1)::BIGINT, 200) AS s FROM (SELECT doc_id, h, unnest(range(0, n - 99)) AS i FROM d WHERE n >= 100)),
     again AS (SELECT doc_id, i FROM (SELECT doc_id, i, row_number() OVER (PARTITION BY s ORDER BY doc_id, i) AS k FROM win) WHERE k > 1),
     step AS (SELECT doc_id, i, CASE WHEN i > lag(i) OVER (PARTITION BY doc_id ORDER BY i) + 100 THEN 1 ELSE 0 END AS new FROM again),
     runs AS (SELECT doc_id, min(i) AS lo, max(i) + 100 AS hi FROM (SELECT doc_id, i, sum(new) OVER (PARTITION BY doc_id ORDER BY i ROWS UNBOUNDED PRECEDING) AS g FROM step) GROUP BY doc_id, g),
     gaps AS (SELECT doc_id, coalesce(lag(hi) OVER (PARTITION BY doc_id ORDER BY lo), 0) AS lo, lo AS hi FROM runs UNION ALL SELECT doc_id, max(hi), NULL FROM runs GROUP BY doc_id UNION ALL SELECT doc_id, 0, NULL FROM d WHERE doc_id NOT IN (SELECT doc_id FROM runs)),
     kept AS (SELECT doc_id, string_agg(substr(h, (2 * lo + 1)::BIGINT, (2 * (coalesce(hi, n) - lo))::BIGINT), '' ORDER BY lo) AS h FROM gaps JOIN d USING (doc_id) GROUP BY doc_id),
     cut AS (SELECT doc_id, sum(hi - lo)::BIGINT AS r, count(*) AS k FROM runs GROUP BY doc_id)
SELECT doc_id, n AS n_bytes, coalesce(r, 0)::BIGINT AS n_removed, coalesce(k, 0)::BIGINT AS n_spans, sha256(unhex(kept.h)) AS kept_sha256 FROM d LEFT JOIN cut USING (doc_id) JOIN kept USING (doc_id)
"""
