"""Near-duplicate detection: MinHash bands for candidates, odd sketches to judge them, full sets to confirm.

Each document is the set of its word shingles (64-bit hashes). ``bands * rows`` MinHash samples give band keys; documents that share a
key are candidates. The same samples are folded into an odd sketch: every (sample number, value) flips one bit, so the population count of
the XOR of two sketches estimates how many samples differ, precisely where similarity is high. Only candidates whose estimate is within ``slack`` of the
threshold are compared on their full sets.

No group is ever expanded into all its pairs. Documents with equal sets are one class with one representative. In each bucket of a band, members are first
compared with the smallest one (the star), whose text is sent once for every ``MEET`` of them. Where that leaves a bucket with several components, every member outside
its largest component meets the members of other components in tiles of bounded size, from which only links come out. Links only need to connect what
all links together would connect, so no component is lost beyond what bands and sketches miss: of links at the threshold itself, with the defaults, a share
of 6.7e-6 and 4.1e-6 (both follow from the binomial distribution of the samples that differ; far fewer above the threshold).

Defined cases: null text counts as empty; a document without words has an empty set and is linked with nothing; with fewer words than a shingle the whole
sequence is its only shingle; A-Z are lower-cased, nothing else; rows with a null id are returned unlinked (component null, kept); a row given twice is
returned twice; an empty table gives no rows; texts are taken whole and other columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_written, text_of, written
from .components import components

_PRIME = np.uint64(0x9E3779B97F4A7C55)
_INVERSE = np.uint64(pow(0x9E3779B97F4A7C55, -1, 1 << 64))
CHUNK = 1 << 20
SKETCH_WORDS = 8  # 64 bits each


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads their bits."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _powers(n: int, base: np.uint64) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    if n:
        out[0] = 1
    return np.multiply.accumulate(out)


def word_hashes(data: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words of the concatenated texts ``data`` and, for each text and the end, the number of words before it.

    ``starts``: offset of each text, and the end. A word's hash is a difference of prefix sums of a polynomial.
    """
    upper = (data >= 65) & (data <= 90)
    data = data + (upper.astype(np.uint8) << 5)
    space = (data == 32) | ((data >= 9) & (data <= 13))
    n = len(data)
    edge = np.zeros(n + 1, bool)
    edge[starts] = True
    first = ~space
    first[1:] &= space[:-1] | edge[1:n]
    last = ~space
    last[:-1] &= space[1:] | edge[1:n]
    begin, end = np.flatnonzero(first), np.flatnonzero(last) + 1
    sums = np.zeros(n + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * _powers(n, _PRIME), out=sums[1:])
    hashes = mixed((sums[end] - sums[begin]) * _powers(n, _INVERSE)[begin] + (end - begin).astype(np.uint64))
    return hashes, np.searchsorted(begin, starts)


def shingle_sets(texts: pa.Array, words: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text, in order."""
    texts = texts.cast(pa.large_binary())
    _, offsets, data = texts.buffers()
    at = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + len(texts) + 1]
    whole = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    factors = [mixed(np.array([k + 1], np.uint64))[0] | np.uint64(1) for k in range(words + 1)]
    k = 0
    while k < len(texts):
        to = max(k + 1, int(np.searchsorted(at, at[k] + CHUNK, "right")) - 1)
        to = min(to, len(texts))
        hashes, bounds = word_hashes(whole[at[k] : at[to]], at[k : to + 1] - at[k])
        n = len(hashes)
        combined = np.zeros(max(n - words + 1, 0), np.uint64)
        for j in range(words):
            combined += hashes[j : n - words + 1 + j] * factors[j] if n >= words else 0
        combined = mixed(combined)
        for d in range(to - k):
            lo, hi = bounds[d], bounds[d + 1]
            if hi - lo >= words:
                yield np.unique(combined[lo : hi - words + 1])
            elif hi > lo:
                short = hashes[lo:hi] * np.array(factors[: hi - lo])
                yield mixed(short.sum(dtype=np.uint64, keepdims=True) + np.array([hi - lo], np.uint64) * factors[words])
            else:
                yield np.zeros(0, np.uint64)
        k = to


class Signer:
    def __init__(self, bands: int, rows: int, seed: int = 11):
        rng = np.random.default_rng(seed)
        n = bands * rows
        self.bands, self.rows = bands, rows
        self.salt = rng.integers(0, 1 << 63, n, dtype=np.uint64)
        self.factor = rng.integers(0, 1 << 63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.number = mixed(np.arange(1, n + 1, dtype=np.uint64))
        self.band_factor = rng.integers(0, 1 << 63, (bands, rows), dtype=np.uint64) | np.uint64(1)

    def samples(self, values: np.ndarray) -> np.ndarray:
        out = np.full(len(self.salt), np.uint64(0xFFFFFFFFFFFFFFFF))
        for k in range(0, len(values), 1024):
            part = (values[k : k + 1024, None] ^ self.salt) * self.factor
            np.minimum(out, part.min(0), out=out)
        return out

    def sign(self, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(band keys, odd sketch as words of 64 bits)."""
        low = mixed(self.samples(values))
        keys = mixed((low.reshape(self.bands, self.rows) * self.band_factor).sum(1, dtype=np.uint64) + np.arange(self.bands, dtype=np.uint64))
        bit = mixed(low + self.number) % np.uint64(64 * SKETCH_WORDS)
        parity = np.bincount(bit.astype(np.int64), minlength=64 * SKETCH_WORDS) & 1
        return keys.view(np.int64), np.packbits(parity.astype(np.uint8)).view(np.int64)


def most_differing_bits(similarity: float, samples: int) -> int:
    """The population count of the XOR at which the odd-sketch estimate falls to ``similarity``."""
    bits = 64 * SKETCH_WORDS
    return int(bits / 2 * (1 - math.exp(-4 * samples * (1 - similarity) / bits)))


def estimate(differing: int, samples: int) -> float:
    """Jaccard similarity estimated from the population count of the XOR of two odd sketches."""
    bits = 64 * SKETCH_WORDS
    return 1 + bits / (4 * samples) * math.log(max(1 - 2 * differing / bits, 1e-9))


def signatures(docs: DataFrame, words: int, bands: int, rows: int) -> DataFrame:
    """doc_id, n_shingles, set_key, bands, sketch of each document; nulls in place of the last three for empty sets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        signer = Signer(bands, rows)
        for batch in batches:
            sizes, keys, band_keys, sketches = [], [], [], []
            for values in shingle_sets(batch.column(1), words):
                sizes.append(len(values))
                if len(values):
                    own, sketch = signer.sign(values)
                    keys.append(hashlib.blake2b(values.tobytes(), digest_size=16).digest())
                    band_keys.append(own)
                    sketches.append(sketch)
                else:
                    keys.append(None)
                    band_keys.append(None)
                    sketches.append(None)
            longs = pa.list_(pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), pa.array(keys, pa.binary()), pa.array(band_keys, longs), pa.array(sketches, longs)], ["doc_id", "n_shingles", "set_key", "bands", "sketch"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text")).mapInArrow(run, "doc_id long, n_shingles long, set_key binary, bands array<long>, sketch array<long>")


def differing_bits(a: str, b: str):
    return sum((F.bit_count(F.get(a, F.lit(k)).bitwiseXOR(F.get(b, F.lit(k)))) for k in range(1, SKETCH_WORDS)), F.bit_count(F.get(a, F.lit(0)).bitwiseXOR(F.get(b, F.lit(0)))))


def _texts_of(docs: DataFrame, ids: DataFrame, most_broadcast: int = 500_000) -> DataFrame:
    """doc_id, text of the documents in ``ids(doc_id)``, a row each; a written table.

    The ids are broadcast while they are at most ``most_broadcast`` (8 bytes each), so that only wanted texts travel; beyond that the join shuffles.
    """
    ids = written(ids.distinct(), "ids")
    few = ids.count() <= most_broadcast
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text")).join(F.broadcast(ids) if few else ids, "doc_id", "left_semi")
    texts = written(texts.dropDuplicates(["doc_id"]), "texts")
    drop_written(ids)
    return texts


MEET = 256


def confirmed(pairs: DataFrame, docs: DataFrame, words: int, percent: int) -> DataFrame:
    """The pairs (a, b) of which 100 * intersection >= percent * union holds on the full sets. Only the texts of documents in pairs travel.

    The partners of b meet it in chunks of about ``MEET``; b comes first in each, and a task holds its set alone while the partners stream by.
    """
    texts = _texts_of(docs, pairs.select(F.col("a").alias("doc_id")).union(pairs.select(F.col("b").alias("doc_id"))))
    centres = written(pairs.groupBy("b").agg(F.ceil(F.count("*") / MEET).cast("int").alias("chunks")), "centres")
    chunked = pairs.join(centres, "b").select("b", F.pmod(F.xxhash64("a"), F.col("chunks")).cast("int").alias("chunk"), "a")
    partners = chunked.join(texts.withColumnRenamed("doc_id", "a"), "a").select("b", "chunk", "a", "text")
    heads = centres.join(texts.withColumnRenamed("doc_id", "b"), "b").select("b", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"), F.lit(None).cast("long").alias("a"), "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        head = np.zeros(0, np.uint64)
        for batch in batches:
            keep = []
            for a, x in zip(batch.column(2), shingle_sets(batch.column(3), words), strict=True):
                if not a.is_valid:
                    head = x
                    keep.append(False)
                    continue
                both = len(np.intersect1d(x, head, assume_unique=True))
                keep.append(100 * both >= percent * (len(x) + len(head) - both) and both > 0)
            yield pa.RecordBatch.from_arrays([batch.column(2), batch.column(0)], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    met = partners.union(heads).repartition("b", "chunk").sortWithinPartitions("b", "chunk", F.asc_nulls_first("a"))
    links = written(met.mapInArrow(run, "a long, b long"), "links")
    drop_written(texts, centres)
    return links


TILE = 512


def _tiles(parts: DataFrame) -> DataFrame:
    """parts with ``tile`` and ``block``: which comparisons of its bucket a row takes part in.

    The members of a bucket's largest component (block M) need not meet each other; all others (S) meet them and each other. Buckets of up to
    ``TILE`` rows are one tile; larger ones are cut into blocks of about that size, and every pair of blocks that has to meet is a tile.
    """
    sizes = parts.groupBy("band", "name").count()
    main = sizes.groupBy("band").agg(F.max_by("name", F.struct("count", "name")).alias("main"), F.max("count").alias("n_main"), F.sum("count").alias("n"))
    blocks = lambda n: F.greatest(F.lit(1), F.ceil(n / TILE).cast("int"))
    rows = parts.join(main, "band").withColumns({"m_blocks": blocks(F.col("n_main")), "s_blocks": blocks(F.col("n") - F.col("n_main")), "is_main": F.col("name") == F.col("main")})
    own = F.pmod(F.xxhash64("rep"), F.when(F.col("is_main"), F.col("m_blocks")).otherwise(F.col("s_blocks"))).cast("int")
    rows = rows.withColumn("own", own)
    each = lambda n, f: F.transform(F.sequence(F.lit(0), F.col(n) - 1), f)
    with_main = lambda i, j: F.concat_ws(":", F.lit("M"), i.cast("string"), j.cast("string"))
    among = each("s_blocks", lambda j: F.concat_ws(":", F.lit("S"), F.least("own", j).cast("string"), F.greatest("own", j).cast("string")))
    tiles = F.when(F.col("n") <= TILE, F.array(F.lit("all"))).when(F.col("is_main"), each("s_blocks", lambda i: with_main(i, F.col("own")))).otherwise(F.concat(among, each("m_blocks", lambda j: with_main(F.col("own"), j))))
    block = F.when(F.col("is_main"), "M").otherwise(F.concat(F.lit("S"), F.col("own").cast("string")))
    return rows.select("band", "rep", "name", block.alias("block"), F.explode(tiles).alias("tile"))


class _Tile:
    """The rows of one tile and which of them may be near each other."""

    def __init__(self, table: pa.Table, most: int):
        self.rep, name, block = (table.column(c).to_pylist() for c in ("rep", "name", "block"))
        tile, band = table.column("tile")[0].as_py(), table.column("band")[0].as_py()
        self.sketch = np.array(table.column("sketch").to_pylist(), np.int64).view(np.uint64)
        self.bands, self.most = None, most
        if "bands" in table.column_names:
            self.bands = np.array(table.column("bands").to_pylist(), np.int64)
            self.number = int(np.flatnonzero(self.bands[0] == band)[0])
        self.label = np.unique(block, return_inverse=True)[1]
        self.main = np.array([x == "M" for x in block])
        self.alone = tile == "all" or tile[0] == "S" and tile.split(":")[1] == tile.split(":")[2]
        self.group = np.unique(name, return_inverse=True)[1]

    def near(self, x: int) -> np.ndarray:
        """Rows of other components that the sketches put near x; given the bands, only in the first that both share, so that every pair comes up in one tile."""
        other = (self.group != self.group[x]) & (self.main | (np.arange(len(self.rep)) > x))
        if not self.alone:
            other &= self.label != self.label[x]
        y = np.flatnonzero(other)
        y = y[np.bitwise_count(self.sketch[y] ^ self.sketch[x]).sum(1) <= self.most]
        return y if self.bands is None else y[(self.bands[y] == self.bands[x]).argmax(1) == self.number]


def _links_within(parts: DataFrame, classes: DataFrame, docs: DataFrame, words: int, percent: int, most: int) -> DataFrame:
    """(a, b): links between components that share a bucket. Pairs are judged where their rows meet and only links leave the task.

    First the sketches say which rows of a tile have any near row of another component; only their texts travel, to be compared on full sets. A link found in a task
    joins its components at once, which spares it the rest.
    """
    keys = "band long, tile string, rep long"
    tiles = _tiles(parts)
    rows = tiles.join(classes.select("rep", "sketch"), "rep").select("band", "tile", "rep", "name", "block", "sketch")

    def mark(table: pa.Table) -> pa.Table:
        tile = _Tile(table, most)
        hit = np.zeros(len(tile.rep), bool)
        for x in np.flatnonzero(~tile.main):
            y = tile.near(x)
            hit[y] = True
            hit[x] |= len(y) > 0
        return table.select(["band", "tile", "rep"]).filter(pa.array(hit, pa.bool_()))

    def judge(table: pa.Table) -> pa.Table:
        tile, found = _Tile(table, most), []
        text = pa.concat_arrays(table.column("text").chunks) if table.column("text").num_chunks else pa.array([], pa.string())
        sets: dict[int, set] = {}

        def shingles(k: int) -> set:
            if k not in sets:
                sets[k] = set(next(shingle_sets(text.slice(k, 1), words)).tolist())
            return sets[k]

        for x in np.flatnonzero(~tile.main):
            for k in tile.near(x):
                if tile.group[k] == tile.group[x]:
                    continue
                a, b = shingles(x), shingles(k)
                if 100 * min(len(a), len(b)) >= percent * max(len(a), len(b)):
                    both = len(a & b)
                    if both and 100 * both >= percent * (len(a) + len(b) - both):
                        found.append((max(tile.rep[x], tile.rep[k]), min(tile.rep[x], tile.rep[k])))
                        tile.group[tile.group == tile.group[k]] = tile.group[x]
        return pa.table({"a": pa.array([a for a, _ in found], pa.int64()), "b": pa.array([b for _, b in found], pa.int64())})

    marked = written(rows.groupBy("band", "tile").applyInArrow(mark, keys), "marked")
    texts = _texts_of(docs, marked.select(F.col("rep").alias("doc_id")))
    whole = classes.select("rep", "bands", "sketch").join(texts.withColumnRenamed("doc_id", "rep"), "rep")
    close = tiles.join(marked, ["band", "tile", "rep"], "left_semi").join(whole, "rep")
    links = written(close.groupBy("band", "tile").applyInArrow(judge, "a long, b long").distinct(), "links")
    drop_written(marked, texts)
    return links


def near_components(docs: DataFrame, *, words: int = 5, percent: int = 80, bands: int = 30, rows: int = 5, slack: float = 0.18) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept."""
    signed = written(signatures(docs, words, bands, rows), "signatures")
    usable = signed.filter("set_key is not null and doc_id is not null")
    classes = written(usable.groupBy("set_key").agg(F.min("doc_id").alias("rep"), F.min_by(F.struct("bands", "sketch"), "doc_id").alias("own")).select("set_key", "rep", "own.bands", "own.sketch"), "classes")
    sketches = classes.select("rep", "sketch")
    members = classes.select("rep", F.explode("bands").alias("band"))
    # written, so that the engine may broadcast it or split the buckets of a large group
    shared = written(members.groupBy("band").agg(F.min("rep").alias("pivot"), F.count("*").alias("n")).filter("n > 1").select("band", "pivot"), "shared")
    buckets = written(members.join(shared, "band"), "buckets")
    drop_written(shared)
    most = most_differing_bits(percent / 100 - slack, bands * rows)

    star = buckets.filter("rep <> pivot").select(F.col("rep").alias("a"), F.col("pivot").alias("b")).distinct()
    star = star.join(sketches.withColumnsRenamed({"rep": "a", "sketch": "sketch_a"}), "a").join(sketches.withColumnsRenamed({"rep": "b", "sketch": "sketch_b"}), "b")
    star = written(star.filter(differing_bits("sketch_a", "sketch_b") <= most).select("a", "b"), "star")
    links = confirmed(star, docs, words, percent)
    named = components(links)
    drop_written(star)

    # buckets that still hold several components
    names = named.withColumnsRenamed({"id": "rep", "component": "name"})
    parts = buckets.join(names, "rep", "left").select("band", "rep", F.coalesce("name", "rep").alias("name"))
    # in a bucket of two, the star has judged the only pair
    several = parts.groupBy("band").agg(F.min("name").alias("low"), F.max("name").alias("high"), F.count("*").alias("n")).filter("low <> high and n > 2").select("band")
    parts = written(parts.join(several, "band"), "parts")
    drop_written(buckets, named)
    more = _links_within(parts, classes, docs, words, percent, most)
    names = components(links.union(more)).withColumnsRenamed({"id": "rep", "component": "name"})
    drop_written(parts, links, more)

    of_class = classes.select("set_key", "rep").join(names, "rep", "left").select(F.col("set_key").alias("_key"), F.coalesce("name", "rep").alias("name"))
    out = signed.select("doc_id", "n_shingles", "set_key").join(of_class, F.col("set_key") == F.col("_key"), "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("name", "doc_id")).alias("component_id")
    return out.select("doc_id", "n_shingles", component, F.coalesce(F.col("doc_id") == F.coalesce("name", "doc_id"), F.lit(True)).alias("kept"))


def drop_near_copies(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with the row of smallest id of each component."""
    gone = near_components(docs, **options).filter("not kept").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


ORACLE = r"""
WITH RECURSIVE d AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
     s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) >= 4 THEN list_transform(range(1, len(ws) - 2), lambda i: array_to_string(ws[i:i + 3], ' ')) WHEN len(ws) > 0 THEN [array_to_string(ws, ' ')] ELSE [] END) AS g FROM d),
     n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
     shared AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
     link AS (SELECT x, y FROM shared JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE 100 * c >= 80 * (p.n + q.n - c)),
     edge AS (SELECT x, y FROM link UNION ALL SELECT y, x FROM link),
     reach AS (SELECT doc_id AS x, doc_id AS y FROM d UNION SELECT r.x, e.y FROM reach r JOIN edge e ON r.y = e.x),
     comp AS (SELECT x AS doc_id, min(y) AS component_id FROM reach GROUP BY x)
SELECT doc_id, coalesce(n, 0)::BIGINT AS n_shingles, component_id, doc_id = component_id AS kept FROM d LEFT JOIN n USING (doc_id) JOIN comp USING (doc_id)
"""
