"""Blocking: nearest target columns of each source column, exact or hashed, with or without predicted tables."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

#: Bytes of query vectors that are sent to every task; beyond them, queries and targets meet in tiles.
BROADCAST_BYTES = 64 << 20
#: Queries and targets of a tile, and cells of a distance matrix held at once.
TILE, CELLS = (4096, 16384), 1 << 22
#: Bytes of target vectors of one group that a task holds to rank all of them; beyond them, tiles meet and the engine ranks.
GROUP_BYTES = 256 << 20
#: Of the targets made into a function: which of them (columns) may be neighbours of some queries (rows).
Pick = Callable[[np.ndarray], Callable[[np.ndarray], np.ndarray]]


def ranked(pairs: DataFrame, by: list[str], order: list, k: int | None, name: str = "rank") -> DataFrame:
    """Dense ranks from 1 in each group; with k, Spark keeps only k rows a group before the shuffle (WindowGroupLimit)."""
    out = pairs.withColumn(name, F.row_number().over(Window.partitionBy(*by).orderBy(*order)))
    return out.filter(F.col(name) <= k) if k is not None else out


def knn(src: DataFrame, tgt: DataFrame, k: int | None, *, metric: str = "l2", digits: int = 6, across: str | None = None, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """query, neighbour, dist, rank: the exact k nearest targets (all without k) of every source row, ties by neighbour. ``src``: query, x; ``tgt``: neighbour, x.

    With ``across``, a column of both sides, neighbours have another value in it than the query and are ranked within each value; it is returned with the neighbour's value.
    A query set of up to ``broadcast_bytes`` goes to the tasks, which multiply it with every batch of targets; a larger one is cut into blocks like the targets, and every
    pair of blocks meets in a task of its own. Either way a batch or tile sends on k rows a query (and value), and the engine merges these.
    """
    return _search(src, tgt, k, metric, digits, across, broadcast_bytes)


def _search(src: DataFrame, tgt: DataFrame, k: int | None, metric: str, digits: int, across: str | None, broadcast_bytes: int, pick: Pick | None = None) -> DataFrame:
    group = [across] if across else []
    src, tgt = (df.select(*group, name, F.col("x").cast("array<double>").alias("x")) for df, name in ((src, "query"), (tgt, "neighbour")))
    kinds = [f"{c} {tgt.schema[c].dataType.simpleString()}" for c in group] + [f"query {src.schema['query'].dataType.simpleString()}", f"neighbour {tgt.schema['neighbour'].dataType.simpleString()}", "dist double"]
    size = src.agg(F.count("*"), F.coalesce(F.max(F.size("x")), F.lit(0))).first()
    if size[0] * size[1] * 8 <= broadcast_bytes:
        shared = src.sparkSession.sparkContext.broadcast(src.toArrow())

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                yield from _nearest(shared.value, pa.Table.from_batches([batch]), k, metric, digits, across, pick).to_batches()

        pairs = tgt.mapInArrow(run, ", ".join(kinds))
    else:
        blocks = [max(1, -(-n // each)) for n, each in zip((size[0], tgt.count()), TILE, strict=True)]
        dealt = lambda df, name, own, n, other, m: df.withColumn(own, F.pmod(F.xxhash64(name), F.lit(n)).cast("int")).withColumn(other, F.explode(F.sequence(F.lit(0), F.lit(m - 1))))
        left = dealt(src, "query", "_q", blocks[0], "_t", blocks[1]).groupBy("_q", "_t")
        right = dealt(tgt, "neighbour", "_t", blocks[1], "_q", blocks[0]).groupBy("_q", "_t")

        def tile(q: pa.Table, t: pa.Table) -> pa.Table:
            return _nearest(q, t, k, metric, digits, across, pick)

        pairs = left.cogroup(right).applyInArrow(tile, ", ".join(kinds))
    return ranked(pairs, [*group, "query"], [F.col("dist").asc() if metric == "l2" else F.col("dist").desc(), F.col("neighbour")], k)


def _matrix(table: pa.Table) -> np.ndarray:
    x = table.column("x").combine_chunks()
    x = x.combine_chunks() if isinstance(x, pa.ChunkedArray) else x
    return np.asarray(x.flatten(), float).reshape(len(x), -1)


def _nearest(q: pa.Table, t: pa.Table, k: int | None, metric: str, digits: int, across: str | None, pick: Pick | None = None) -> pa.Table:
    """The k best of the targets for every query (and value of ``across``): [across,] query, neighbour, dist."""
    names = [*([across] if across else []), "query", "neighbour", "dist"]
    parts = []
    if len(q) and len(t):
        t = t.sort_by("neighbour")  # a lower column of the matrix wins a tie
        values = t.column(across).unique() if across else [None]
        for value in values:
            own_q, own_t = q, t
            if across:
                own_t = t.filter(pa.compute.equal(t.column(across), value))
                own_q = q.filter(pa.compute.not_equal(q.column(across), value))
            a, b = _matrix(own_q), _matrix(own_t)
            step, picked = max(1, CELLS // max(len(own_t), 1)), pick(b) if pick else None
            for i in range(0, len(own_q), step):
                rows, cols, dist = _best(a[i : i + step], b, k, metric, digits, picked(a[i : i + step]) if picked else None)
                cells = [own_q.column("query").take(pa.array(rows + i)), own_t.column("neighbour").take(pa.array(cols)), pa.array(dist)]
                parts.append(pa.table([*([pa.array([value.as_py()] * len(rows), t.schema.field(across).type)] if across else []), *cells], names=names))
    if parts:
        return pa.concat_tables(parts)
    types = [*([t.schema.field(across).type] if across else []), q.schema.field("query").type, t.schema.field("neighbour").type, pa.float64()]
    return pa.table([pa.array([], x) for x in types], names=names)


def _best(q: np.ndarray, t: np.ndarray, k: int | None, metric: str, digits: int, among: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of q, row of t, rounded distance) of the k best, only ``among`` some pairs if given. A matrix product finds who can be among them, however many tie; they are then computed one by one."""
    size_q, size_t = (q * q).sum(1), (t * t).sum(1)
    if among is not None and (k is None or k >= len(t) or among.mean() < 0.05):
        rows, cols = np.nonzero(among)
    elif k is not None and k < len(t):
        product = q @ t.T
        if metric == "l2":
            score = np.maximum(size_q[:, None] + size_t[None] - 2 * product, 0)
        else:
            length = np.sqrt(size_q)[:, None] * np.sqrt(size_t)[None]
            score = -np.divide(product, length, out=np.zeros_like(product), where=length > 0)
        if among is not None:
            score[~among] = np.inf
        last, slack = np.partition(score, k - 1, axis=1)[:, k - 1], 10.0**-digits
        noise = 1e-12 * (1 + size_q + size_t.max())
        last = (np.sqrt(last + noise) + slack) ** 2 + noise if metric == "l2" else last + slack + 1e-12
        near = score <= last[:, None]
        rows, cols = np.nonzero(near if among is None else near & among)
    else:
        rows, cols = np.repeat(np.arange(len(q)), len(t)), np.tile(np.arange(len(t)), len(q))
    dist = np.empty(len(rows))
    for i in range(0, len(rows), 1 << 16):
        x, y = q[rows[i : i + (1 << 16)]], t[cols[i : i + (1 << 16)]]
        if metric == "l2":
            dist[i : i + len(x)] = np.sqrt(((x - y) ** 2).sum(1))
        else:
            length = np.sqrt((x * x).sum(1)) * np.sqrt((y * y).sum(1))
            dist[i : i + len(x)] = np.divide((x * y).sum(1), length, out=np.zeros(len(x)), where=length > 0)
    dist = np.round(dist, digits) + 0.0
    order = np.lexsort((cols, dist if metric == "l2" else -dist, rows))
    rows, cols, dist = rows[order], cols[order], dist[order]
    place = np.arange(len(rows)) - np.searchsorted(rows, rows)
    keep = place < (k if k is not None else len(t))
    return rows[keep], cols[keep], dist[keep]


def _tiles(left: DataFrame, right: DataFrame, by: str, size: tuple[int, int]) -> tuple:
    """Both sides grouped into tiles of about ``size`` rows within each value of ``by``: (query, .., x) and (neighbour, .., x)."""
    count = lambda df, n, name: df.groupBy(by).agg(F.ceil(F.count("*") / F.lit(n)).cast("int").alias(name))
    blocks = F.broadcast(count(left, size[0], "_m").join(count(right, size[1], "_n"), by))  # a row for each value
    dealt = lambda df, name, own, n, other, m: df.join(blocks, by).withColumn(own, F.pmod(F.xxhash64(name), F.col(n)).cast("int")).withColumn(other, F.explode(F.sequence(F.lit(0), F.col(m) - 1))).drop("_m", "_n")
    return dealt(left, "query", "_q", "_m", "_t", "_n").groupBy(by, "_q", "_t"), dealt(right, "neighbour", "_t", "_n", "_q", "_m").groupBy(by, "_q", "_t")


def nearest_each(src: DataFrame, tgt: DataFrame, k: int | None, *, by: str = "table_id", metric: str = "l2", digits: int = 6) -> DataFrame:
    """query, neighbour, dist, ``by``: the k nearest (at most k from a tile, and more if a value of ``by`` has several tiles; all without k) of the targets with the query's value of ``by``.

    ``src``: query (of any type), ``by``, x; a query may have several values. ``tgt``: neighbour, ``by``, x, one row for a neighbour and value.
    """
    left, right = (df.select(name, by, F.col("x").cast("array<double>").alias("x")) for df, name in ((src, "query"), (tgt, "neighbour")))
    kinds = T.StructType([left.schema["query"], right.schema["neighbour"], left.schema[by], T.StructField("dist", T.DoubleType())])

    def tile(key: tuple[pa.Scalar, ...], q: pa.Table, t: pa.Table) -> pa.Table:
        found = _nearest(q, t, k, metric, digits, None)
        return found.append_column(by, pa.array([key[0].as_py()] * len(found), key[0].type)).select(["query", "neighbour", by, "dist"])

    a, b = _tiles(left, right, by, TILE if k is not None else (max(1, CELLS // TILE[1]), TILE[1]))
    return a.cogroup(b).applyInArrow(tile, kinds)


def knn_within(src: DataFrame, tgt: DataFrame, allowed: DataFrame, k: int, *, metric: str = "l2", digits: int = 6) -> DataFrame:
    """The same among allowed tables only: ``allowed(query, table_id)`` turns the search into tiles within a table, each of which sends on k rows a query."""
    asked = src.select("query", "x").join(allowed.select("query", "table_id").distinct(), "query")
    rows = nearest_each(asked, tgt, k, metric=metric, digits=digits).select("query", "neighbour", "dist").distinct()
    return ranked(rows, ["query"], [F.col("dist").asc() if metric == "l2" else F.col("dist").desc(), F.col("neighbour")], k)


def cosine_ranks(src: DataFrame, tgt: DataFrame, by: str, *, digits: int = 6, group_bytes: int = GROUP_BYTES) -> DataFrame:
    """query, neighbour, dist (cosine, 0 if either vector is all zeros), rank: all targets of the query's value of ``by``, ties by neighbour.

    The queries of a value are cut into blocks, its targets copied to each; a task holds them and ranks a few queries at a time, so that pairs are neither shuffled nor
    sorted by the engine. Targets of more than ``group_bytes`` meet the queries in tiles instead, and the engine ranks.
    """
    left, right = (df.select(by, name, F.col("x").cast("array<double>").alias("x")) for df, name in ((src, "query"), (tgt, "neighbour")))
    most = right.groupBy(by).agg((F.count("*") * F.max(F.size("x")) * 8).alias("n")).agg(F.max("n")).first()[0]
    if (most or 0) > group_bytes:
        return ranked(nearest_each(left, right, None, by=by, metric="cosine", digits=digits).drop(by), ["query"], [F.col("dist").desc(), F.col("neighbour")], None)
    kinds = {name: df.schema[name].dataType for df, name in ((left, "query"), (right, "neighbour"))}
    blocks = F.broadcast(left.groupBy(by).agg(F.ceil(F.count("*") / F.lit(TILE[0] // 8)).cast("int").alias("_m")))  # a row for each value
    asked = left.join(blocks, by).select(by, F.pmod(F.xxhash64("query"), F.col("_m")).cast("int").alias("_q"), "query", F.lit(None).cast(kinds["neighbour"]).alias("neighbour"), "x")
    held = right.join(blocks, by).select(by, F.explode(F.sequence(F.lit(0), F.col("_m") - 1)).alias("_q"), F.lit(None).cast(kinds["query"]).alias("query"), "neighbour", "x")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = pa.Table.from_batches(list(batches))
        q, t = rows.filter(pa.compute.is_valid(rows.column("query"))), rows.filter(pa.compute.is_valid(rows.column("neighbour"))).sort_by("neighbour")
        if not len(q) or not len(t):  # a block that no query fell into, or a value of one side only
            return
        ids, neighbours = (x.column(n).combine_chunks() for x, n in ((q, "query"), (t, "neighbour")))
        a, b = _unit_rows(_matrix(q)), _unit_rows(_matrix(t))
        one, bits, step = 10**digits, len(t).bit_length(), max(1, CELLS // 8 // len(t))
        for i in range(0, len(q), step):
            key = ((one - np.rint(a[i : i + step] @ b.T * one).astype(np.int64)) << bits) | np.arange(len(t))  # less for a higher cosine, then for a lower neighbour
            key.sort(axis=1)
            key, n = key.ravel(), len(key)
            yield pa.RecordBatch.from_arrays([
                ids.take(pa.array(np.repeat(np.arange(i, i + n), len(t)))), neighbours.take(pa.array(key & ((1 << bits) - 1))),
                pa.array((one - (key >> bits)) / one), pa.array(np.tile(np.arange(1, len(t) + 1, dtype=np.int32), n)),
            ], names=["query", "neighbour", "dist", "rank"])

    return asked.union(held).groupBy(by, "_q").applyInArrow(run, f"query {kinds['query'].simpleString()}, neighbour {kinds['neighbour'].simpleString()}, dist double, rank int")


def _unit_rows(x: np.ndarray) -> np.ndarray:
    length = np.sqrt((x * x).sum(1))[:, None]
    return np.divide(x, length, out=np.zeros_like(x), where=length > 0)


def lsh(src: DataFrame, tgt: DataFrame, k: int, *, planes: int = 8, tables: int = 32, probes: int = 8, seed: int = 5, digits: int = 6, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """Approximate: rows that share the sign pattern of ``planes`` random hyperplanes in any of ``tables`` tables are candidates, ranked exactly.

    A query also looks into the buckets across each of the ``probes`` planes nearest to it, and across the two nearest at once. Buckets are bit sets over the targets
    of a batch or tile (see ``knn``), so that pairs stay where they are found and k rows a query travel on.
    """
    dim = src.select(F.size("x")).first()
    normals = np.random.default_rng(seed).standard_normal((tables, planes, dim[0] if dim else 1))
    powers = 1 << np.arange(planes)

    def pick(targets: np.ndarray) -> Callable[[np.ndarray], np.ndarray]:
        own = ((np.einsum("tpd,nd->ntp", normals, targets) > 0) * powers).sum(2)
        buckets = [np.packbits(np.arange(1 << planes)[:, None] == own[:, j], axis=1) for j in range(tables)]

        def candidates(queries: np.ndarray) -> np.ndarray:
            side = np.einsum("tpd,nd->ntp", normals, queries)
            at = ((side > 0) * powers).sum(2)
            flip = powers[np.argsort(abs(side), axis=2, kind="stable")[:, :, : max(probes, 2)]]
            looks = [at, *([at ^ flip[:, :, j] for j in range(probes)] + [at ^ flip[:, :, 0] ^ flip[:, :, 1]] if probes else [])]
            found = np.zeros((len(queries), buckets[0].shape[1]), np.uint8)
            for j, held in enumerate(buckets):
                for look in looks:
                    found |= held[look[:, j]]
            return np.unpackbits(found, axis=1, count=len(targets)).view(bool)

        return candidates

    return _search(src.select("query", "x"), tgt.select("neighbour", "x"), k, "l2", digits, None, broadcast_bytes, pick)
