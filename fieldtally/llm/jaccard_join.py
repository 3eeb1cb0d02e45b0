"""Exact n-gram Jaccard self-join in the metric space of shingle sets.

Distance is one minus Jaccard similarity, a metric.  The steps:

1. Every whole text becomes its set of 5-word shingles (hashes).  Equal sets are one point.
2. Cells: each point is entered in the cells of its first shingles in hash order, so many that a
   linked partner shares several.  Points that share too few with all others together have no partner.
3. The full sets of the rest are entered in cells.  Cells of up to CROWD points give pairs with the
   exact number of uncrowded shingles they share, which mostly decides the pair; where it
   and the crowded shingles together leave it open, the distance is computed.
4. Pairs that share crowded cells alone are between points that are almost wholly crowded.  Of
   those, the most central one of a cell becomes a pivot, and the points within the radius of it, computed
   exactly, its Voronoi region: they are linked to it, and no pair inside is looked at.
5. Windows: pairs of regions that meet in a crowded cell again, among as many as a linked pair
   must share one of, are judged by the pivots' distance d.  Up to the radius they are linked; beyond radius
   + both region radii the triangle inequality rules out every pair; between the two, boundary
   members are compared with the other pivot, and those that it still leaves with one another.
   Two regions that other links already join to one component have nothing to add and are left out.
6. Links are joined to components.

No pair of a dense region is enumerated, and no component misses a link between different sets.
Equal sets meet first in their Arrow batch, so a group of copies is as many rows as there are batches.

Edge cases: null and empty texts have no shingles and are their own component; with fewer
than five words the whole sequence is the one shingle; rows that share a doc_id are one
document and all their links count; a null doc_id has a null component; columns other than
``doc_id`` and ``text`` are ignored by the join and kept by :func:`keep_first`.  An empty
table gives an empty table.  Shingles are compared as 48-bit hashes, and counted as 64-bit ones.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import WordHashes, as_bytes, drop_suffix, read_documents, scratch, ship, window_hashes
from .components import components

WORDS = 5
SIMILARITY = 75  # percent
RADIUS = 1 - SIMILARITY / 100
EXTRA = 5  # percent
CROWD = 64
HOMES = 8
#: Pairs that are compared in one task at a time; their sets are its memory.
BUCKET_PAIRS = 1024
_BYTES = 6
#: Bits of the filter that keeps the texts of points that aren't compared from being shuffled; a fixed bound.
_FILTER_BITS = 1 << 27
_CELL_ROWS = 2_000_000

_SEEN = WordHashes()


def shingles(text: bytes, k: int = WORDS) -> np.ndarray:
    """The sorted distinct 64-bit hashes of the text's k-word shingles (A-Z lower-cased)."""
    found = text.lower().split()
    if not found:
        return np.empty(0, np.uint64)
    if len(found) < k:
        return np.array([xxhash.xxh3_64_intdigest(b" ".join(found), 7)], np.uint64)
    return np.unique(window_hashes(_SEEN.of(found), k))


def prefix_size(n: int) -> int:
    """How many of n shingles, in hash order, are entered: as many as a partner must share one
    of, and a twentieth more, so that a partner of many shingles must share several."""
    return n - -(-SIMILARITY * n // 100) + 1 + EXTRA * n // 100


def pack(grams: np.ndarray) -> bytes:
    return (grams >> np.uint64(16)).astype("<u8").view(np.uint8).reshape(-1, 8)[:, :_BYTES].tobytes()


def unpack(raw: bytes) -> np.ndarray:
    out = np.zeros((len(raw) // _BYTES, 8), np.uint8)
    out[:, :_BYTES] = np.frombuffer(raw, np.uint8).reshape(-1, _BYTES)
    return out.view("<u8").ravel()


def distance(a: np.ndarray, b: np.ndarray) -> tuple[int, int]:
    """(intersection, union) of two sorted sets."""
    both = np.concatenate([a, b])
    both.sort()
    common = int((both[1:] == both[:-1]).sum())
    return common, len(both) - common


def _points(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sizes, digests, prefixes, seen = [], [], [], set()
        for text in as_bytes(batch.column(1)):
            g = shingles(text)
            sizes.append(len(g))
            digest = xxhash.xxh3_128_digest(g.tobytes()) if len(g) else None
            digests.append(digest)
            fresh = digest is not None and digest not in seen
            seen.add(digest)
            prefixes.append(pack(g[: prefix_size(len(g))]) if fresh else None)
        yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(sizes, pa.int64()), pa.array(digests, pa.binary()), pa.array(prefixes, pa.binary())], ["doc_id", "n", "digest", "prefix"])


def _slots(batches: Iterator[pa.RecordBatch], bits: int) -> Iterator[pa.RecordBatch]:
    flags = np.zeros(bits, bool)
    for batch in batches:
        flags[_slot(batch.column(0).to_numpy(zero_copy_only=False), bits)] = True
    yield pa.RecordBatch.from_arrays([pa.array([np.packbits(flags).tobytes()], pa.binary())], ["flags"])


def _slot(ids: np.ndarray, bits: int) -> np.ndarray:
    return ((ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(20)).astype(np.int64) & (bits - 1)


def _sets_of(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """(digest, grams) of at least the wanted documents: a filter of bounded size spares most of the others."""
    spark = docs.sparkSession
    bits = min(_FILTER_BITS, max(1 << 16, 1 << int(ids.count() * 16).bit_length()))
    parts = ids.coalesce(4).mapInArrow(lambda b: _slots(b, bits), "flags binary").collect()  # four times the filter's size
    flags = np.zeros(bits // 8, np.uint8)
    for row in parts:
        flags |= np.frombuffer(bytes(row["flags"]), np.uint8)
    shared = spark.sparkContext.broadcast(flags)

    def run(batches):
        wanted = np.unpackbits(shared.value).view(bool)
        for batch in batches:
            own = batch.column(0).cast(pa.int64())
            mask = wanted[_slot(own.fill_null(0).to_numpy(zero_copy_only=False), bits)] & own.is_valid().to_numpy(zero_copy_only=False)
            found = [shingles(x) for x in as_bytes(batch.filter(pa.array(mask)).column(1))]
            found = [g for g in found if len(g)]
            yield pa.RecordBatch.from_arrays([pa.array([xxhash.xxh3_128_digest(g.tobytes()) for g in found], pa.binary()), pa.array([pack(g) for g in found], pa.binary())], ["digest", "grams"])

    return drop_suffix(docs, ["doc_id", "text"]).mapInArrow(run, "digest binary, grams binary")


def _compare(key: tuple, pairs: pa.Table, sets: pa.Table) -> pa.Table:
    """The pairs of a bucket, each measured; sets has every end once."""
    grams = dict(zip(sets.column("node").to_pylist(), map(unpack, sets.column("grams").to_pylist()), strict=True))
    found = [distance(grams[a], grams[b]) for a, b in zip(pairs.column("a").to_pylist(), pairs.column("b").to_pylist(), strict=True)]
    common, union = np.array(found, np.int64).reshape(-1, 2).T
    return pa.table({"a": pairs.column("a"), "b": pairs.column("b"), "common": common, "total": union})


def _homes_of(crowd: DataFrame) -> DataFrame:
    """The HOMES smallest crowded cells of each point."""
    order = Window.partitionBy("node").orderBy("cell")
    return crowd.withColumn("place", F.row_number().over(order)).where(F.col("place") <= HOMES).drop("place")


def measured(sets: DataFrame, pairs: DataFrame, name: str) -> DataFrame:
    """(a, b) pairs of points -> (a, b, d, linked), exactly, as a written table.  sets: node, grams; pairs: a written table.

    Pairs are dealt to buckets of about BUCKET_PAIRS by both ends, so that a point of many pairs is spread, and its set
    is shuffled once for each bucket that needs it."""
    buckets = max(1, -(-pairs.count() // BUCKET_PAIRS))
    dealt = pairs.select("a", "b", F.pmod(F.xxhash64("a", "b"), F.lit(buckets)).alias("bucket"))
    ends = dealt.select(F.col("bucket").alias("place"), F.explode(F.array("a", "b")).alias("node")).distinct()
    wanted = ends.join(sets.select("node", "grams"), "node").select("place", "node", "grams")
    out = dealt.groupBy("bucket").cogroup(wanted.groupBy("place")).applyInArrow(_compare, "a long, b long, common long, total long")
    out = out.select("a", "b", (1 - F.col("common") / F.col("total")).alias("d"), (F.col("common") * 100 >= F.col("total") * SIMILARITY).alias("linked"))
    return scratch(pairs.sparkSession, out, name)


def _least_overlap(n, m):
    """The fewest common shingles of a linked pair of sizes n and m (columns)."""
    return F.ceil((n + m) * SIMILARITY / (100 + SIMILARITY) - 1e-9)


def _possible(n, m):
    return (n * 100 >= m * SIMILARITY) & (m * 100 >= n * SIMILARITY)


def fewest_shared(n):
    """How many of the entered shingles of a set of n a linked partner shares at least (column): the partner's size may
    be from t*n to n/t, and what lies beyond a prefix is shared at most once each."""
    small = F.ceil(n * SIMILARITY / 100)
    large = F.greatest(F.least(F.floor(n * 100 / SIMILARITY), F.floor(small * 100 / SIMILARITY)), n)
    need = _least_overlap(small, large) - F.ceil(large * SIMILARITY / 100) + 1 + F.floor(large * EXTRA / 100)
    return F.greatest(need - 1, F.lit(1))


def _dealt(parts: int):
    """(node, grams) rows -> for each part one row with all of the batch's (cell, node) entries."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raws = batch.column(1).to_pylist()
            if not raws:
                continue
            cell = (unpack(b"".join(raws))).astype(np.int64)
            node = np.repeat(batch.column(0).to_numpy(zero_copy_only=False), [len(x) // _BYTES for x in raws])
            part = (cell * 0x9E3779B1 >> 7) % parts
            order = np.argsort(part, kind="stable")
            cell, node, part = cell[order], node[order], part[order]
            cut = np.flatnonzero(np.append(True, part[1:] != part[:-1])) if len(part) else np.empty(0, np.int64)
            ends = np.append(cut[1:], len(part))
            blobs = [pack(cell[a:b].astype(np.uint64) << np.uint64(16)) + node[a:b].astype("<i8").tobytes() for a, b in zip(cut.tolist(), ends.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(part[cut], pa.int64()), pa.array(blobs, pa.binary())], ["part", "entries"])

    return run


def _entries(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of a part: (cell, node) in order, each once, with where each cell begins and how many nodes it has."""
    cells, nodes = [], []
    for raw in table.column("entries").to_pylist():
        n = len(raw) // (_BYTES + 8)
        cells.append(unpack(raw[: n * _BYTES]).astype(np.int64))
        nodes.append(np.frombuffer(raw, "<i8", n, n * _BYTES))
    cell, node = np.concatenate(cells), np.concatenate(nodes)
    order = np.lexsort((node, cell))
    cell, node = cell[order], node[order]
    fresh = np.append(True, (cell[1:] != cell[:-1]) | (node[1:] != node[:-1]))
    cell, node = cell[fresh], node[fresh]
    first = np.flatnonzero(np.append(True, cell[1:] != cell[:-1]))
    return cell, node, first, np.diff(np.append(first, len(cell)))


def _sharing(table: pa.Table, count: int) -> pa.Table:
    """How many of each point's cells in this part have another point too, packed by slices of points."""
    _, node, _, size = _entries(table)
    found, n = np.unique(node[np.repeat(size > 1, size)], return_counts=True)
    which = (found * 0x9E3779B1 >> 9) % count
    slices = np.unique(which)
    packed = [np.stack([found[which == s], n[which == s]]).astype("<i8").tobytes() for s in slices.tolist()]
    return pa.table({"slice": slices.astype(np.int64), "counts": pa.array(packed, pa.binary())})


def _added(table: pa.Table) -> pa.Table:
    """The sums of a slice's counts."""
    both = np.concatenate([np.frombuffer(raw, "<i8").reshape(2, -1) for raw in table.column("counts").to_pylist()], 1)
    found, at = np.unique(both[0], return_inverse=True)
    return pa.table({"node": found, "shared": np.bincount(at, both[1]).astype(np.int64)})


def _meetings(table: pa.Table, crowd: int) -> pa.Table:
    """Pairs of points with the number of uncrowded cells they share, and the entries of crowded cells."""
    cell, node, first, size = _entries(table)
    a, b = [], []
    for width in np.unique(size[(size > 1) & (size <= crowd)]).tolist():
        block = node[first[size == width][:, None] + np.arange(width)]
        i, j = np.triu_indices(width, 1)
        a.append(block[:, i].ravel())
        b.append(block[:, j].ravel())
    a = np.concatenate(a) if a else np.empty(0, np.int64)
    b = np.concatenate(b) if b else np.empty(0, np.int64)
    order = np.lexsort((b, a))
    a, b = a[order], b[order]
    cut = np.flatnonzero(np.append(True, (a[1:] != a[:-1]) | (b[1:] != b[:-1]))) if len(a) else np.empty(0, np.int64)
    shared = np.diff(np.append(cut, len(a)))
    crowded = np.repeat(size > crowd, size)
    kinds = np.append(np.zeros(len(cut), np.int32), np.ones(crowded.sum(), np.int32))
    return pa.table({"crowded": kinds, "a": np.append(a[cut], cell[crowded]), "b": np.append(b[cut], node[crowded]), "shared": np.append(shared, np.ones(crowded.sum(), np.int64)).astype(np.int64)})


def _parts(entries: int) -> int:
    return max(1, -(-entries // _CELL_ROWS))


def link_documents(docs: DataFrame, crowd_size: int = CROWD) -> DataFrame:
    """(doc_id, n_shingles, component_id) of every row, the same for any ``crowd_size``."""
    spark = docs.sparkSession
    ship(spark)
    table = scratch(spark, drop_suffix(docs, ["doc_id", "text"]).mapInArrow(_points, "doc_id long, n long, digest binary, prefix binary"), "points")
    named = table.where("n > 0 and doc_id is not null")
    # A point is named by the smallest doc_id that has it; points that share that id (repeated ids) by a hash below zero.
    firsts = named.groupBy("digest").agg(F.min("doc_id").alias("rep"), F.max("n").alias("n"))
    alone = F.count("*").over(Window.partitionBy("rep")) == 1
    nodes = scratch(spark, firsts.select("digest", "rep", "n", F.when(alone, F.col("rep")).otherwise(-F.abs(F.xxhash64("digest") % (1 << 62)) - 1).alias("node")), "nodes")

    # Who may have a partner at all.
    entries = int(nodes.agg(F.coalesce(F.sum(F.lit(1) + F.floor(F.col("n") * (100 - SIMILARITY + EXTRA) / 100)), F.lit(0)).alias("s")).first()["s"])
    points = table.where("prefix is not null").select("digest", "prefix").join(nodes, "digest").select("node", "prefix")
    parts = _parts(entries)
    shared = points.mapInArrow(_dealt(parts), "part long, entries binary").groupBy("part").applyInArrow(lambda t: _sharing(t, max(16, parts)), "slice long, counts binary")
    shared = shared.groupBy("slice").applyInArrow(_added, "node long, shared long")
    rest = shared.join(nodes, "node").where(F.col("shared") >= fewest_shared(F.col("n")))
    rest = scratch(spark, rest.select("node", "rep", "digest", "n"), "rest")
    sets = _sets_of(docs, rest.select("rep")).join(rest, "digest").dropDuplicates(["node"]).select("node", "n", "grams")
    sets = scratch(spark, sets, "sets")

    # Uncrowded cells give pairs, crowded ones regions.
    total = int(sets.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("s")).first()["s"])
    dealt = sets.select("node", "grams").mapInArrow(_dealt(_parts(total)), "part long, entries binary")
    met = scratch(spark, dealt.groupBy("part").applyInArrow(lambda t: _meetings(t, crowd_size), "crowded int, a long, b long, shared long"), "meetings")
    crowd = met.where("crowded = 1").select(F.col("a").alias("cell"), F.col("b").alias("node"))
    owed = crowd.groupBy("node").agg(F.count("*").alias("owed"))
    known = scratch(spark, sets.select("node", "n").join(owed, "node", "left").fillna(0, ["owed"]), "known")
    links, pairs, satellites, near = _regions(spark, sets, known, crowd)
    p, q = (known.select(*[F.col(c).alias(f"{c}_{s}") for c in known.columns]) for s in "pq")
    judged = met.where("crowded = 0").groupBy("a", "b").agg(F.sum("shared").alias("shared")).join(p, F.col("a") == F.col("node_p")).join(q, F.col("b") == F.col("node_q"))
    enough = _least_overlap(F.col("n_p"), F.col("n_q"))
    judged = judged.where(_possible(F.col("n_p"), F.col("n_q")) & (F.col("shared") + F.least("owed_p", "owed_q") >= enough))
    judged = scratch(spark, judged.select("a", "b", (F.col("shared") >= enough).alias("sure")), "judged")
    links.append(judged.where("sure").select(F.col("a").alias("u"), F.col("b").alias("v")))
    inside = satellites.select("node", "region")
    # Two points of one region are linked to its pivot anyway.
    unsure = judged.where("not sure").join(inside.select(F.col("node").alias("a"), F.col("region").alias("ra")), "a", "left").join(inside.select(F.col("node").alias("b"), F.col("region").alias("rb")), "b", "left")
    unsure = scratch(spark, unsure.where(~F.coalesce(F.coalesce("ra", "a") == F.coalesce("rb", "b"), F.lit(False))).select("a", "b"), "unsure")
    if not unsure.isEmpty():
        links.append(measured(sets, unsure, "decided").where("linked").select(F.col("a").alias("u"), F.col("b").alias("v")))
    centres = None if pairs.isEmpty() else measured(sets, pairs, "centres")
    if centres is not None:
        links.append(_edges(centres))

    twice = named.join(nodes.select("digest", "node"), "digest").select("doc_id", "node").distinct()
    ends = twice.groupBy("doc_id").agg(F.min("node").alias("u"), F.count("*").alias("m")).where("m > 1").drop("m")
    links.append(twice.join(ends, "doc_id").select("u", F.col("node").alias("v")))
    found = components(spark, _union(links))
    labels = nodes.join(found, "node", "left").select("digest", "rep", F.coalesce("component", "node").alias("label"))
    if centres is not None and (more := _windows(spark, sets, centres, satellites, found)):
        labels = _merged(spark, labels, found, _union(more))
    least = labels.groupBy("label").agg(F.min("rep").alias("component_id"))
    labels = labels.join(least, "label").select("digest", "component_id")
    home = table.select("doc_id", F.col("n").alias("n_shingles"), "digest").join(labels, "digest", "left")
    return home.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id")).alias("component_id"))


def _regions(spark: SparkSession, sets: DataFrame, known: DataFrame, crowd: DataFrame) -> tuple[list[DataFrame], DataFrame, DataFrame, DataFrame]:
    """(links to pivots, pairs of regions that may hold a link without an uncrowded cell, satellites (node, region, d), links).

    Such a pair's common cells are all crowded, so both points are almost wholly crowded: central.  The most central
    point of a cell is its pivot."""
    central = known.where(F.col("owed") >= F.ceil(F.col("n") * SIMILARITY / 100))
    inner = scratch(spark, crowd.join(central, "node"), "inner")
    homes = _homes_of(inner)
    ratio = F.round(F.col("owed") / F.col("n"), 6)
    centres = homes.groupBy("cell").agg(F.max(F.struct(ratio.alias("r"), F.col("n").alias("n"), (-F.col("node")).alias("p"))).alias("x")).select("cell", (-F.col("x.p")).alias("pivot"))
    votes = homes.join(centres, "cell").where("node <> pivot").groupBy("node", "pivot").agg(F.count("*").alias("votes"))
    best = votes.groupBy("node").agg(F.max(F.struct(F.col("votes"), (-F.col("pivot")).alias("p"))).alias("x"))
    stars = scratch(spark, best.select(F.col("node").alias("a"), (-F.col("x.p")).alias("b")), "stars")
    near = measured(sets, stars, "near").where("linked")
    pivots = near.select(F.col("b").alias("node")).distinct()
    satellites = scratch(spark, near.select(F.col("a").alias("node"), F.col("b").alias("region"), "d").join(pivots, "node", "left_anti"), "satellites")
    # As many crowded cells as a central point must share one of.
    order = Window.partitionBy("node").orderBy("cell")
    entered = inner.withColumn("place", F.row_number().over(order)).where(F.col("place") <= F.col("owed") - F.ceil(F.col("n") * SIMILARITY / 100) + 1)
    placed = entered.join(satellites.select("node", "region"), "node", "left").select("cell", F.coalesce("region", "node").alias("region"), "n", "owed")
    placed = placed.groupBy("cell", "region").agg(F.min("n").alias("low"), F.max("n").alias("high"), F.max("owed").alias("owed"))
    several = placed.groupBy("cell").agg(F.count("*").alias("m")).where("m > 1").drop("m")
    placed = scratch(spark, placed.join(several, "cell"), "placed")
    p, q = (placed.select("cell", *[F.col(c).alias(f"{c}_{s}") for c in ("region", "low", "high", "owed")]) for s in "pq")
    small = F.greatest(F.least("low_p", "low_q"), F.ceil(F.greatest("low_p", "low_q") * SIMILARITY / 100))
    fits = (F.col("high_p") * 100 >= F.col("low_q") * SIMILARITY) & (F.col("high_q") * 100 >= F.col("low_p") * SIMILARITY)
    reach = F.least("owed_p", "owed_q") >= _least_overlap(small, F.greatest(F.col("low_p"), F.col("low_q")))
    pairs = p.join(q, (p["cell"] == q["cell"]) & (F.col("region_p") < F.col("region_q")) & fits & reach).select(F.col("region_p").alias("a"), F.col("region_q").alias("b")).distinct()
    done = near.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    pairs = scratch(spark, pairs.join(done, ["a", "b"], "left_anti"), "pairs")
    return [near.select(F.col("a").alias("u"), F.col("b").alias("v"))], pairs, satellites, near


def _edges(measured_pairs: DataFrame) -> DataFrame:
    return measured_pairs.where("linked").select(F.col("a").alias("u"), F.col("b").alias("v"))


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for more in frames[1:]:
        out = out.unionByName(more)
    return out


def _labelled(frame: DataFrame, found: DataFrame, column: str, label: str) -> DataFrame:
    """The component of a column's points so far; a point without any link is its own."""
    known = found.select(F.col("node").alias(column), F.col("component").alias("_component"))
    return frame.join(known, column, "left").withColumn(label, F.coalesce("_component", column)).drop("_component")


def _merged(spark: SparkSession, labels: DataFrame, found: DataFrame, edges: DataFrame) -> DataFrame:
    """The labels after further links, as components of components."""
    joined = _labelled(_labelled(edges, found, "u", "cu"), found, "v", "cv").select(F.col("cu").alias("u"), F.col("cv").alias("v"))
    above = components(spark, joined).select(F.col("node").alias("label"), "component")
    return labels.join(above, "label", "left").select("digest", "rep", F.coalesce("component", "label").alias("label"))


def _windows(spark: SparkSession, sets: DataFrame, centres: DataFrame, satellites: DataFrame, found: DataFrame) -> list[DataFrame]:
    """Links among the regions of each pair, by the triangle inequality, where they aren't in one component by other links."""
    out = []
    radii = satellites.groupBy("region").agg(F.max("d").alias("radius"))
    open_ = centres.where("not linked").join(radii.select(F.col("region").alias("a"), F.col("radius").alias("ra")), "a", "left").join(radii.select(F.col("region").alias("b"), F.col("radius").alias("rb")), "b", "left")
    open_ = open_.fillna(0.0, ["ra", "rb"]).where(f"d <= {RADIUS} + ra + rb + 1e-9 and ra + rb > 0").select("a", "b", "d", "ra", "rb")
    open_ = _labelled(_labelled(open_, found, "a", "ca"), found, "b", "cb").where("ca <> cb").drop("ca", "cb")
    if (open_ := scratch(spark, open_, "open")).isEmpty():
        return out
    member = satellites.select("region", F.col("node").alias("x"), F.col("d").alias("dx"))
    left = open_.join(member, F.col("a") == F.col("region")).where(f"dx + rb >= d - {RADIUS} - 1e-9").select(F.col("x").alias("m"), F.col("b").alias("c"), F.col("a").alias("own"), F.col("rb").alias("reach"))
    right = open_.join(member, F.col("b") == F.col("region")).where(f"dx + ra >= d - {RADIUS} - 1e-9").select(F.col("x").alias("m"), F.col("a").alias("c"), F.col("b").alias("own"), F.col("ra").alias("reach"))
    boundary = scratch(spark, left.unionByName(right), "boundary")
    if boundary.isEmpty():
        return out
    asked = scratch(spark, boundary.select(F.col("m").alias("a"), F.col("c").alias("b")).distinct(), "asked")
    seen = measured(sets, asked, "seen")
    out.append(_edges(seen))
    judged = boundary.join(seen.select(F.col("a").alias("m"), F.col("b").alias("c"), "d", "linked"), ["m", "c"])
    done = judged.where("linked").select(F.least("own", "c").alias("p"), F.greatest("own", "c").alias("q")).distinct()
    left_in = judged.where(f"not linked and d <= {RADIUS} + reach + 1e-9").select("m", F.least("own", "c").alias("p"), F.greatest("own", "c").alias("q"), (F.col("own") < F.col("c")).alias("first"))
    left_in = left_in.join(done, ["p", "q"], "left_anti")
    met = left_in.where("first").select("p", "q", F.col("m").alias("a")).join(left_in.where("not first").select("p", "q", F.col("m").alias("b")), ["p", "q"]).select("a", "b").distinct()
    if not (met := scratch(spark, met, "met")).isEmpty():
        out.append(_edges(measured(sets, met, "members")))
    return out


def keep_first(docs: DataFrame) -> DataFrame:
    """The rows, unchanged, whose doc_id is their component's smallest, and all without an id.  Of rows that share an id the first by text stays."""
    found = link_documents(docs).where("doc_id = component_id").select("doc_id").distinct()
    kept = docs.join(found, "doc_id", "left_semi").select(*docs.columns)
    kept = kept.withColumn("_place", F.row_number().over(Window.partitionBy("doc_id").orderBy("text"))).where("_place = 1").drop("_place")
    # A null id is linked with nothing and equals no other.
    return kept.unionByName(docs.where("doc_id is null"))


def op2_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_documents(read_documents(spark, sf_dir))
