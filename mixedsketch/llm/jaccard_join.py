"""Self-join of documents on the Jaccard similarity of their word shingles.

Exact, and without comparing all pairs:

1. Equal shingle sets collapse to one class; a class is a node from here on.
2. Every class gets a 512-bit hashed *parity* bitmap.  Each shingle outside the
   intersection flips one bit, so ``popcount(a xor b)`` never exceeds the size
   of the symmetric difference, which bounds the overlap from above.  Sets too
   large for 512 bits have a second bitmap as wide as their size band asks.
3. A one-hop star around min-hash leaders links the bulk of any large group of
   near copies in linear work.  It only saves work: nothing depends on its recall.
4. Prefix filter: a class can only reach the threshold with another one if they
   share a shingle within the first ``n - ceil(t*n) + 1`` of a global order.  The
   order puts frequent shingles last; frequencies come from a Count-Min row over
   the whole corpus, of a fixed width, so what is broadcast does not grow.
5. Classes that share a prefix shingle form a tile.  Tiles are dealt to tasks by
   ranges of (shingle, star, size), so one that holds a third of all rows is cut
   by many tasks.  Small tiles give their pairs within the size band; larger ones
   become blocks, and each pair of blocks whose size ranges are compatible, and
   which are not both of one star, compares bitmaps in one numpy pass.
6. What the bitmaps let through is intersected exactly on sorted arrays.
7. Links are contracted to connected components.

Shingles are 64-bit hashes of words; two different shingles of a pair share one
with probability below 1e-12.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel
from .graph import components
from .workspace import Workspace, ship

ORDER_BITS = 20  # cells of the frequency order: 4 MB a task while counting, 1 MB when broadcast
SLICE_BITS = 14
SIG_WORDS = 8
WIDE_FROM = 700  # sets from this size on saturate 64 * SIG_WORDS bits
STARS = 4
SMALL_TILE = 32
BLOCK = 1024
BROADCAST_IDS = 500_000
SAME = ["n", "k1", "k2"]  # size and two sums of hashes: what rows of one class share

_STAR_SALT = [np.uint64((2 * i + 1) * 0x5851F42D4C957F2D % 2**64) for i in range(STARS)]
_SIG_SALT = np.uint64(0xA0761D6478BD642F)
_CLASS_SALT = [np.uint64(0xE7037ED1A0B428DB), np.uint64(0x8EBC6AF09C88C6E3)]

_PROFILE = ["id long", "n long", "k1 long", "k2 long"] + [f"m{i} long" for i in range(STARS)] + [f"s{i} long" for i in range(SIG_WORDS)] + ["wide binary", "slice int", "cells binary"]


def overlap_needed(n: np.ndarray | int, percent: int):
    """Smallest overlap with which a set of ``n`` can reach the threshold with any other."""
    return -(-percent * n // 100)


def _wide_bitmap(values: np.ndarray) -> bytes:
    """Parity bitmap of at least half as many bits as the set has members, a power of two; halves fold by xor."""
    bits = max(64 * SIG_WORDS, 1 << int(len(values) // 2 - 1).bit_length())
    odd = np.bincount((kernel.mix64(values ^ _SIG_SALT) & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8)).tobytes()


def _wide_distance(x: np.ndarray, y: np.ndarray) -> int:
    """Differing bits at the narrower width."""
    if len(x) > len(y):
        x, y = y, x
    while len(y) > len(x):
        y = y[: len(y) // 2] ^ y[len(y) // 2 :]
    return int(np.bitwise_count(x ^ y).sum())


def _profile(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = np.zeros(1 << ORDER_BITS, dtype=np.int64)
        names = [x.split()[0] for x in _PROFILE]
        types = [pa.int64()] * (4 + STARS + SIG_WORDS) + [pa.binary(), pa.int32(), pa.binary()]
        for batch in batches:
            ids = batch.column("id")
            for lo, hi, values, cut in kernel.shingle_sets(batch.column("text"), size):
                n = np.diff(cut)
                rows = hi - lo
                cols = np.zeros((2 + STARS + SIG_WORDS, rows), dtype=np.uint64)
                full = np.flatnonzero(n)
                if len(full):
                    at = cut[full]
                    for i, salt in enumerate(_CLASS_SALT):
                        cols[i, full] = np.add.reduceat(kernel.mix64(values ^ salt), at)
                    for i, salt in enumerate(_STAR_SALT):
                        cols[2 + i, full] = np.minimum.reduceat(kernel.mix64(values ^ salt), at)
                    bit = (kernel.mix64(values ^ _SIG_SALT) & np.uint64(64 * SIG_WORDS - 1)).astype(np.int64)
                    bit += np.repeat(np.arange(rows, dtype=np.int64) * (64 * SIG_WORDS), n)
                    odd = np.bincount(bit, minlength=rows * 64 * SIG_WORDS) & 1
                    cols[2 + STARS :] = np.packbits(odd.astype(np.uint8)).view(np.uint64).reshape(rows, SIG_WORDS).T
                    cells += np.bincount((values >> np.uint64(64 - ORDER_BITS)).astype(np.int64), minlength=len(cells))
                wide = [_wide_bitmap(values[cut[i] : cut[i + 1]]) if n[i] >= WIDE_FROM else None for i in range(rows)]
                out = [ids.slice(lo, rows), pa.array(n)] + [pa.array(c.view(np.int64)) for c in cols] + [pa.array(wide, pa.binary())]
                yield pa.RecordBatch.from_arrays([*out, pa.nulls(rows, pa.int32()), pa.nulls(rows, pa.binary())], names=names)
        per = cells.reshape(-1, 1 << SLICE_BITS)
        used = np.flatnonzero(per.any(axis=1))
        if len(used):
            blobs = [zlib.compress(per[i].astype(np.uint32).tobytes(), 1) for i in used]
            yield pa.RecordBatch.from_arrays([pa.nulls(len(used), t) for t in types[:-2]] + [pa.array(used.astype(np.int32)), pa.array(blobs, pa.binary())], names=names)

    return run


def _add_slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total: dict[int, np.ndarray] = {}
    for batch in batches:
        for i, blob in zip(batch.column("slice").to_pylist(), batch.column("cells").to_pylist(), strict=True):
            got = np.frombuffer(zlib.decompress(blob), dtype=np.uint32).astype(np.uint64)
            total[i] = total[i] + got if i in total else got
    if total:
        rank = [np.log2(v.astype(np.float64) + 1).astype(np.uint8).tobytes() for v in total.values()]
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array(rank, pa.binary())], names=["slice", "rank"])


def frequency_order(profiles: DataFrame, spark: SparkSession) -> np.ndarray:
    """log2 of the Count-Min row of all shingles, one byte a cell (fixed size)."""
    rank = np.zeros((1 << (ORDER_BITS - SLICE_BITS), 1 << SLICE_BITS), dtype=np.uint8)
    for row in profiles.filter("slice IS NOT NULL").select("slice", "cells").repartition(1 << (ORDER_BITS - SLICE_BITS), "slice").mapInArrow(kernel.tidy(_add_slices), "slice int, rank binary").collect():
        rank[row["slice"]] = np.frombuffer(bytes(row["rank"]), dtype=np.uint8)
    return rank.reshape(-1)


def _prefixes(size: int, percent: int, order):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rank = order.value
        for batch in batches:
            ids = batch.column("id")
            for lo, hi, values, cut in kernel.shingle_sets(batch.column("text"), size):
                n = np.diff(cut)
                owner = np.repeat(np.arange(hi - lo), n)
                cell = rank[(values >> np.uint64(64 - ORDER_BITS)).astype(np.int64)].astype(np.uint64)
                # rank in the top byte, then the hash: one sort key that all documents order alike
                key = (cell << np.uint64(56)) | (kernel.mix64(values) >> np.uint64(8))
                for i in range(hi - lo):
                    key[cut[i] : cut[i + 1]].sort()
                take = np.where(n > 0, n - overlap_needed(n, percent) + 1, 0)
                keep = (np.arange(len(key)) - np.repeat(cut[:-1], n)) < np.repeat(take, n)
                offsets = np.concatenate(([0], np.cumsum(take))).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(key[keep].view(np.int64)))
                yield pa.RecordBatch.from_arrays([ids.slice(lo, hi - lo), pa.array(n), lists], names=["id", "n", "keys"])

    return run


def _tiles(percent: int):
    """Rows sorted by (key, lane, n, id): pairs of small tiles, block rows and block headers of large ones.

    The first and the last tile of a task may go on in its neighbours, so they
    become blocks whatever their size; block numbers are unique over all tasks.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 32

        def emit(kind, *cols):
            k = len(cols[0])
            cols = [pa.array(c, pa.int64()) for c in cols] + [pa.nulls(k, pa.int64())] * (5 - len(cols))
            return pa.RecordBatch.from_arrays([pa.array(np.full(k, kind, dtype=np.int32)), *cols], names=["kind", *"abcde"])

        def blocks(rows):
            """Blocks of rows of one tile, each with the range of its sizes and its star if it has only one."""
            nonlocal number
            for at in range(0, rows.shape[1], BLOCK):
                part = rows[:, at : at + BLOCK]
                k = part.shape[1]
                star = part[3, 0] if (part[3] == part[3, 0]).all() else None
                yield emit(1, part[0], np.full(k, number), part[2])
                yield emit(2, part[0, :1], [number], [part[1].min()], [part[1].max()], [star])
                number += 1

        def pairs(rows, i, j):
            """Candidates (i, j) of a tile held whole."""
            small, large = np.minimum(rows[1, i], rows[1, j]), np.maximum(rows[1, i], rows[1, j])
            ok = (100 * small >= percent * large) & (rows[3, i] != rows[3, j]) & (rows[2, i] != rows[2, j])
            if ok.any():
                x, y = rows[2, i[ok]], rows[2, j[ok]]
                yield emit(0, np.minimum(x, y), np.maximum(x, y))

        rest = np.zeros((4, 0), dtype=np.int64)
        opened = True  # the tile at the front of ``rest`` may have begun earlier
        for batch in batches:
            now = np.stack([batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("key", "n", "id", "star")])
            rest = np.concatenate([rest, now], axis=1)
            if not rest.shape[1]:
                continue
            bounds = np.concatenate(([0], np.flatnonzero(np.diff(rest[0])) + 1, [rest.shape[1]]))
            sizes = np.diff(bounds)[:-1]  # the last tile may go on in the next batch
            if len(sizes):
                if opened:
                    yield from blocks(rest[:, : bounds[1]])
                    sizes[0] = 0
                opened = False
                two = bounds[np.flatnonzero(sizes == 2)]
                if len(two):
                    yield from pairs(rest, two, two + 1)
                for g in np.flatnonzero(sizes > 2):
                    tile = rest[:, bounds[g] : bounds[g + 1]]
                    if (tile[3] == tile[3, 0]).all():
                        continue
                    if sizes[g] > SMALL_TILE:
                        yield from blocks(tile)
                    else:
                        yield from pairs(tile, *np.triu_indices(sizes[g], 1))
            rest = rest[:, bounds[-2] :]
            whole = rest.shape[1] // BLOCK * BLOCK
            if whole >= 2 * BLOCK:  # never hold an unbounded tile
                yield from blocks(rest[:, :whole])
                rest, opened = rest[:, whole:], True
        yield from blocks(rest)

    return run


def _block_pair(percent: int):
    """One block pair: all its bitmaps at once, and only cross-star pairs that the bound lets through."""

    def run(both: pa.Table) -> pa.Table:
        side = both.column("side").to_numpy()
        left, right = both.filter(pa.array(side == 0)), both.filter(pa.array(side == 1))

        def unpack(t):
            sig = np.stack([t.column(f"s{i}").to_numpy().view(np.uint64) for i in range(SIG_WORDS)]) if t.num_rows else np.zeros((SIG_WORDS, 0), np.uint64)
            return t.column("id").to_numpy(), t.column("n").to_numpy(), t.column("star").to_numpy(), sig

        ia, na, ca, sa = unpack(left)
        ib, nb, cb, sb = unpack(right)
        xs, ys = [], []
        for i in range(len(ia)):
            ham = np.zeros(len(ib), dtype=np.int64)
            for w in range(SIG_WORDS):
                ham += np.bitwise_count(sb[w] ^ sa[w, i])
            top = np.minimum(np.minimum(na[i], nb), (na[i] + nb - ham) // 2)
            ok = ((100 + percent) * top >= percent * (na[i] + nb)) & (cb != ca[i]) & (ib != ia[i])
            if ok.any():
                hit = ib[ok]
                xs.append(np.minimum(hit, ia[i]))
                ys.append(np.maximum(hit, ia[i]))
        empty = np.zeros(0, dtype=np.int64)
        return pa.table({"a": np.concatenate(xs) if xs else empty, "b": np.concatenate(ys) if ys else empty}).group_by(["a", "b"]).aggregate([])

    return run


def _arrays(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("id")
            for lo, hi, values, cut in kernel.shingle_sets(batch.column("text"), size):
                blobs = [values[cut[i] : cut[i + 1]].tobytes() for i in range(hi - lo)]
                yield pa.RecordBatch.from_arrays([ids.slice(lo, hi - lo), pa.array(blobs, pa.binary())], names=["id", "arr"])

    return run


def _intersect(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column("x"), batch.column("y"), strict=True):
                p, q = np.frombuffer(x.as_buffer(), dtype=np.uint64), np.frombuffer(y.as_buffer(), dtype=np.uint64)
                if len(p) > len(q):
                    p, q = q, p
                at = np.searchsorted(q, p)
                both = int((q[np.minimum(at, len(q) - 1)] == p).sum()) if len(q) else 0
                keep.append(both > 0 and 100 * both >= percent * (len(p) + len(q) - both))
            mask = pa.array(keep, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column("a").filter(mask), batch.column("b").filter(mask)], names=["a", "b"])

    return run


def _bounded(pairs: DataFrame, nodes: DataFrame, percent: int) -> DataFrame:
    """Pairs whose bitmaps still allow the threshold."""
    sig = [f"s{i}" for i in range(SIG_WORDS)]
    left = nodes.select(F.col("id").alias("a"), F.col("n").alias("na"), F.col("star").alias("ca"), *[F.col(s).alias(f"l{s}") for s in sig])
    right = nodes.select(F.col("id").alias("b"), F.col("n").alias("nb"), F.col("star").alias("cb"), *[F.col(s).alias(f"r{s}") for s in sig])
    ham = sum((F.bit_count(F.col(f"l{s}").bitwiseXOR(F.col(f"r{s}"))) for s in sig), F.lit(0))
    top = F.least("na", "nb", F.expr("(na + nb - ham) div 2"))
    joined = pairs.join(left, "a").join(right, "b").withColumn("ham", ham.cast("long"))
    return joined.filter(F.lit(100 + percent) * top >= F.lit(percent) * (F.col("na") + F.col("nb"))).select("a", "b").distinct()


def _wide_bound(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, y = batch.column("x"), batch.column("y")
            total = batch.column("na").to_numpy() + batch.column("nb").to_numpy()
            ham = np.zeros(len(total), dtype=np.int64)
            for i in np.flatnonzero(x.is_valid().to_numpy(zero_copy_only=False) & y.is_valid().to_numpy(zero_copy_only=False)):
                ham[i] = _wide_distance(np.frombuffer(x[i].as_buffer(), dtype=np.uint8), np.frombuffer(y[i].as_buffer(), dtype=np.uint8))
            keep = pa.array((100 + percent) * ((total - ham) // 2) >= percent * total)
            yield pa.RecordBatch.from_arrays([batch.column("a").filter(keep), batch.column("b").filter(keep)], names=["a", "b"])

    return run


def _verified(pairs: DataFrame, profiles: DataFrame, docs: DataFrame, size: int, percent: int, work: Workspace, name: str) -> DataFrame:
    """Pairs that reach the threshold: wide bitmaps of large sets first, then sorted arrays of what is left."""
    pairs = work.save(pairs, f"{name}-bounded")
    wide = profiles.filter("slice IS NULL AND id IS NOT NULL").select("id", "n", F.col("wide").alias("w"))
    both = pairs.join(wide.toDF("a", "na", "x"), "a").join(wide.toDF("b", "nb", "y"), "b")
    pairs = work.save(both.mapInArrow(kernel.tidy(_wide_bound(percent)), "a long, b long").distinct(), f"{name}-pairs")
    ids = work.save(pairs.select(F.col("a").alias("id")).union(pairs.select(F.col("b").alias("id"))).distinct(), f"{name}-ids")
    few = ids.count() <= BROADCAST_IDS
    wanted = docs.join(F.broadcast(ids) if few else ids, "id", "left_semi")
    arrays = work.save(wanted.mapInArrow(kernel.tidy(_arrays(size)), "id long, arr binary"), f"{name}-arrays")
    both = pairs.join(arrays.select(F.col("id").alias("a"), F.col("arr").alias("x")), "a").join(arrays.select(F.col("id").alias("b"), F.col("arr").alias("y")), "b")
    return work.save(both.mapInArrow(kernel.tidy(_intersect(percent)), "a long, b long").distinct(), f"{name}-links")


def _numbered(docs: DataFrame, id_col: str, text_col: str, work: Workspace) -> tuple[DataFrame, DataFrame | None]:
    """((id, text) without null ids, and the numbers that rows with null ids have been given).

    Such rows are written once, with numbers beyond all ids, so that they are
    nodes like others.  If ids leave no room above or below, null rows link nothing.
    """
    docs = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    n, low, high = docs.agg(F.sum(F.col("id").isNull().cast("long")), F.min("id"), F.max("id")).first()
    if not n:
        return docs, None
    room = 1 << 62
    if (high or 0) < room:
        number = F.lit(max(high or 0, 0) + 1) + F.monotonically_increasing_id()
    elif low > -room:
        number = F.lit(min(low, 0) - 1) - F.monotonically_increasing_id()
    else:
        return docs, None
    lost = work.save(docs.filter("id IS NULL").select(number.alias("id"), "text"), "unnamed")
    return docs.filter("id IS NOT NULL").unionByName(lost), lost.select("id")


def _block_heads(tiles: DataFrame, name: str) -> DataFrame:
    return tiles.filter("kind = 2").selectExpr("a AS key", f"b AS {name}", f"c AS {name}_least", f"d AS {name}_most", f"e AS {name}_star")


@dataclass
class Linked:
    """Rows with their class key, classes with their smallest id, and links (a, b) between classes."""

    rows: DataFrame
    classes: DataFrame
    links: DataFrame
    unnamed: DataFrame | None


def _linked(docs: DataFrame, id_col: str, text_col: str, size: int, percent: int, work: Workspace, every: bool) -> Linked:
    """The links; ``every`` one of them, or only as many as connect what is connected."""
    spark = docs.sparkSession
    ship(spark)
    docs, unnamed = _numbered(docs, id_col, text_col, work)
    sig = [f"s{i}" for i in range(SIG_WORDS)]
    mins = [f"m{i}" for i in range(STARS)]

    profiles = work.save(docs.mapInArrow(kernel.tidy(_profile(size)), ", ".join(_PROFILE)), "profiles")
    rows = profiles.filter("slice IS NULL").select("id", "n", "k1", "k2", *mins, *sig)
    classes = work.save(rows.filter("n > 0").groupBy(*SAME).agg(F.min("id").alias("id"), *[F.first(c).alias(c) for c in [*mins, *sig]]), "classes")
    nodes = classes.filter("id IS NOT NULL")
    lone = nodes.withColumn("star", F.col("id"))
    star_links = None
    if every:
        starred = lone.select("id", "n", *sig, "star", F.lit(-1).cast("long").alias("lane"))
    else:  # star: each node against the smallest node of its min-hash groups
        hubs = nodes.select("id", F.posexplode(F.array(*mins)).alias("p", "m"))
        heads = hubs.groupBy("p", "m").agg(F.min("id").alias("a"), F.max("id").alias("last")).filter("a <> last").drop("last")
        star_pairs = hubs.join(heads, ["p", "m"]).filter("a <> id").select("a", F.col("id").alias("b")).distinct()
        star_links = _verified(_bounded(star_pairs, lone, percent), profiles, docs, size, percent, work, "star")
        stars = work.save(star_links.groupBy(F.col("b").alias("id")).agg(F.min("a").alias("star")), "stars")
        big = stars.groupBy("star").count().filter(F.col("count") >= BLOCK).select("star", F.col("star").alias("lane"))
        stars = stars.join(big, "star", "left")
        starred = nodes.select("id", "n", *sig).join(stars, "id", "left").withColumn("star", F.coalesce("star", "id"))
        starred = work.save(starred.select("id", "n", *sig, "star", F.coalesce("lane", F.lit(-1).cast("long")).alias("lane")), "starred")

    order = spark.sparkContext.broadcast(frequency_order(profiles, spark))
    keys = work.save(docs.mapInArrow(kernel.tidy(_prefixes(size, percent, order)), "id long, n long, keys array<long>"), "prefixes")
    keyed = keys.join(starred.select("id", "n", "star", "lane"), ["id", "n"]).select(F.explode("keys").alias("key"), "lane", "n", "id", "star")
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    by_key = ["key", "lane", "n", "id"]
    tiles = work.save(
        keyed.repartitionByRange(parts, *by_key).sortWithinPartitions(*by_key).mapInArrow(kernel.tidy(_tiles(percent)), "kind int, a long, b long, c long, d long, e long"), "tiles"
    )
    small = tiles.filter("kind = 0").select("a", "b").distinct()
    block_rows = tiles.filter("kind = 1").select(F.col("a").alias("key"), F.col("b").alias("block"), F.col("c").alias("id")).join(starred.drop("lane"), "id")
    block_pairs = _block_heads(tiles, "hi").join(_block_heads(tiles, "lo"), "key").filter(
        f"hi >= lo AND 100 * least(hi_most, lo_most) >= {percent} * greatest(hi_least, lo_least) AND coalesce(hi_star <> lo_star, true)"
    )
    block_pairs = block_pairs.select("key", "hi", "lo")
    by = ["key", "hi", "lo"]
    sides = [block_pairs.join(block_rows.withColumnRenamed("block", name), ["key", name]).select(*by, F.lit(i).alias("side"), "id", "n", "star", *sig) for i, name in enumerate(("hi", "lo"))]
    large = sides[0].union(sides[1]).groupBy(*by).applyInArrow(_block_pair(percent), "a long, b long")
    pairs = _bounded(small, starred, percent).union(large).distinct()
    links = _verified(pairs, profiles, docs, size, percent, work, "tile")
    return Linked(rows.select("id", *SAME), classes.select(*SAME, "id"), links if every else star_links.union(links), unnamed)


def _by_class(rows: DataFrame, named: DataFrame) -> DataFrame:
    """``rows`` with the columns of ``named`` for their class (null where the set is empty)."""
    return rows.join(named.select(*[F.col(c).alias(f"q_{c}") for c in SAME], *[c for c in named.columns if c not in SAME]), F.expr(" AND ".join(f"{c} = q_{c}" for c in SAME)), "left").drop(*[f"q_{c}" for c in SAME])


def _restore(ids: DataFrame, unnamed: DataFrame | None, column: str = "id") -> DataFrame:
    """Numbers given to rows without an id become nulls again."""
    if unnamed is None:
        return ids
    return ids.join(unnamed.select(F.col("id").alias(column), F.lit(True).alias("lost")), column, "left").withColumn(column, F.when(F.col("lost").isNull(), F.col(column))).drop("lost")


def jaccard_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 5, percent: int = 80) -> DataFrame:
    """Per row of ``docs``: (doc_id, n_shingles, component_id).

    Texts are lower-cased (A-Z), cut into words at ASCII white space and turned
    into the set of distinct ``size``-word shingles; a text of fewer words is
    one shingle.  Two rows link when ``100 * |A & B| >= percent * |A | B|``;
    ``component_id`` is the smallest id reachable by links.

    Nulls and empty texts: ``n_shingles`` 0, linked with nothing, component is
    the own id.  A row with a null id links others like any row but never names
    a component, so one all of whose partners have null ids has a null
    component.  Repeated rows are kept; rows that share an id are one node.
    Extra columns are ignored.  An empty table gives an empty result.
    """
    work = Workspace(docs.sparkSession, "jaccard")
    got = _linked(docs, id_col, text_col, size, percent, work, every=False)
    found = components(got.links.select(F.col("a").alias("u"), F.col("b").alias("v")), work)
    work.drop("starred", "stars", "prefixes", "tiles", *[f"{stage}-{table}" for stage in ("star", "tile") for table in ("bounded", "pairs", "ids", "arrays", "links")])  # nothing reads them again
    named = got.classes.withColumnRenamed("id", "class_id").join(found.select(F.col("node").alias("class_id"), "component"), "class_id", "left")
    named = named.select(*SAME, F.coalesce("component", "class_id").alias("component"))
    if got.unnamed is not None:  # the smallest id that a row really has
        rows = got.rows.join(got.unnamed.withColumn("lost", F.lit(True)), "id", "left")
        real = _by_class(rows.filter("lost IS NULL AND n > 0").drop("lost"), named).groupBy("component").agg(F.min("id").alias("least"))
        named = named.join(real, "component", "left").select(*SAME, F.col("least").alias("component"))
    out = _restore(_by_class(got.rows, named), got.unnamed)
    return out.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("component")).otherwise(F.col("id")).alias("component_id"))


def jaccard_links(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 5, percent: int = 80) -> tuple[DataFrame, DataFrame]:
    """(links, members): every link (a, b) between classes of equal sets, and per row (doc_id, class_id, class_size, n_links).

    A class is named by its smallest id; rows of one class link each other, and
    ``n_links`` counts all rows but itself that a row links.  Rows with empty
    sets have no class and no links.  A class of null ids alone has a number
    beyond all ids.  Everything else is as in ``jaccard_components``, which
    needs fewer links than there are.
    """
    work = Workspace(docs.sparkSession, "jaccard-links")
    got = _linked(docs, id_col, text_col, size, percent, work, every=True)
    sizes = got.rows.filter("n > 0").groupBy(*SAME).agg(F.count("*").alias("class_size"))
    named = work.save(_by_class(sizes, got.classes.withColumnRenamed("id", "class_id")), "named")
    both = got.links.union(got.links.select("b", "a")).join(named.select(F.col("class_id").alias("b"), F.col("class_size").alias("k")), "b")
    degree = both.groupBy(F.col("a").alias("class_id")).agg(F.sum("k").alias("others"))
    named = named.join(degree, "class_id", "left")
    members = _restore(_by_class(got.rows, named), got.unnamed)
    n_links = F.coalesce(F.col("class_size") - 1 + F.coalesce("others", F.lit(0)), F.lit(0))
    return got.links, members.select(F.col("id").alias("doc_id"), "class_id", "class_size", n_links.cast("long").alias("n_links"))


def op7_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Classes of ``documents`` at four words and 85 percent."""
    return jaccard_components(spark.read.parquet(f"{sf_dir}/documents.parquet"), size=4, percent=85)


_FOLD = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

OP7_SQL = rf"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all({_FOLD}, '[^\x20\x09-\x0D]+') AS w FROM documents),
sh AS (SELECT DISTINCT doc_id, array_to_string(w[i : i + 3], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 1) + 1)) AS i FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
o AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS o FROM sh a JOIN sh b ON a.s = b.s AND a.doc_id < b.doc_id GROUP BY ALL),
e AS (SELECT a, b FROM o JOIN n x ON a = x.doc_id JOIN n y ON b = y.doc_id WHERE 100 * o >= 85 * (x.n + y.n - o)),
both_ways AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
r AS (SELECT doc_id AS x, doc_id AS y FROM d UNION SELECT r.x, f.b FROM r JOIN both_ways f ON r.y = f.a)
SELECT d.doc_id, coalesce(n, 0) AS n_shingles, c AS component_id FROM d LEFT JOIN n USING (doc_id) JOIN (SELECT x AS doc_id, min(y) AS c FROM r GROUP BY x) USING (doc_id)
"""
