"""Near-duplicate grouping by SuperMinHash signatures, banding, verification and union-find.

Each element of a document's shingle set draws a permutation of the signature's places, round by round; in round j it
offers j plus a random fraction to its place, and each place keeps the least offer. A document is done as soon as all
its places hold less than the next round can offer, so large sets take one or two rounds. The places of a signature
are negatively correlated, which lowers the variance of the estimate.

Documents of equal sets are one numbered node. Bands of signature values give buckets; of buckets with the same members, which
close copies share in most bands, the one of the first band stands for all. Documents meet their candidates in two ways,
neither of which lists the pairs of a large group:

1. stars: every member of a bucket is compared with the bucket's hub, the member that shares the largest buckets with
   others; of its hubs each document keeps the one of the best estimate. Confirmed links are joined to components.
2. leftovers: in buckets that still hold several components, members of different components are estimated against each
   other, in blocks of a bounded number of rows; a pair is estimated in the first bucket that it shares. Members of
   one component need no further link, so groups of copies are gone by now. Only pairs of a likely estimate leave a block.

A pair is confirmed on the full sets: 100 * intersection >= 75 * union. An estimate over 480 places that is more than 4.5
standard deviations below the threshold saves the comparison. With 40 bands of 4 values, a pair at exactly 0.75
shares no band with a chance of 2.5e-7, and a more similar pair with less.

Defined results: words are what ASCII white space separates after A-Z are lower-cased; null and wordless texts have
an empty set and no link; texts of fewer than five words have their whole sequence as one shingle; texts of any length
are read whole; rows repeated whole, and rows of one id with different texts, are each judged by their text; null ids
come after all others, so a group has a null id only where it has no other; an empty table gives an empty result; other
columns of the input are ignored, whatever their names.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, filled, once_per_worker, over_batches
from .components import components
from .dealt import beside, join_dealt, join_salted, salts_of, sizes_of, small
from .exact_dedup import frequent_digests
from .hashing import GOLDEN, WordHashes, mix, runs

WORDS = 5
BANDS, ROWS = 40, 4
PLACES = BANDS * ROWS
MORE = 2  # further signatures, for estimates alone
#: Over this estimate a pair is compared in full: 0.75 less 4.5 standard deviations of as many independent places.
LIKELY = 0.75 - 4.5 * (0.75 * 0.25 / ((1 + MORE) * PLACES)) ** 0.5
#: Leftovers of a bucket are compared in blocks of about this many rows on either side.
BLOCK = 1_024
CHUNK = 200_000
EMPTY = np.uint32(0xFFFFFFFF)


def shingles(text: bytes, hashes: WordHashes, n: int = WORDS) -> np.ndarray:
    """The sorted set of 64-bit hashes of the runs of n words."""
    words = text.lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    h = hashes(words)
    return np.unique(runs(h, min(n, len(h))))


def signatures(sets: list[np.ndarray], places: int = PLACES, seed: int = 0) -> np.ndarray:
    """SuperMinHash of each set: places of (round << 24 | fraction); sets x places."""
    out = np.full((len(sets), places), EMPTY, np.uint32)
    flat, elements = out.ravel(), np.concatenate([*sets, np.zeros(0, np.uint64)])
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    for at in range(0, len(elements), CHUNK):
        chunk, own = elements[at : at + CHUNK], owner[at : at + CHUNK]
        order = np.tile(np.arange(places, dtype=np.uint8), (len(chunk), 1)).ravel()
        live = np.arange(len(chunk))
        for j in range(places):
            with np.errstate(over="ignore"):
                bits = mix(chunk[live] + GOLDEN * np.uint64(j + 1 + 256 * seed))
            other = live * places + j + ((bits & np.uint64(0xFFFFFFFF)) % np.uint64(places - j)).astype(np.int64)
            place = order[other].astype(np.int64)
            order[other] = order[live * places + j]
            offer = (np.uint64(j << 24) | (bits >> np.uint64(40))).astype(np.uint32)
            np.minimum.at(flat, own[live] * places + place, offer)
            first, last = own[live[0]], own[live[-1]] + 1
            done = out[first:last].max(axis=1) < np.uint32(min((j + 1) << 24, 0xFFFFFFFF))
            live = live[~done[own[live] - first]]
            if not len(live):
                break
    return out


def bands(signature: np.ndarray, count: int = BANDS) -> np.ndarray:
    """A 64-bit key of each band; the band's number is part of it."""
    parts = signature.reshape(len(signature), count, -1).astype(np.uint64)
    with np.errstate(over="ignore"):
        key = np.broadcast_to(np.arange(1, count + 1, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93), parts.shape[:2]).copy()
        for i in range(parts.shape[2]):
            key = mix(key * GOLDEN + parts[:, :, i])
    return key.view(np.int64)


def marks(sets: list[np.ndarray], first: np.ndarray) -> list[bytes]:
    """For estimates: two bytes of each place of the banded signature, then one byte of each place of the others."""
    first = (first & np.uint32(0xFFFF)).astype(np.uint16)
    others = [(signatures(sets, seed=k) & np.uint32(0xFF)).astype(np.uint8) for k in range(1, MORE + 1)]
    return [b"".join([x.tobytes() for x in row]) for row in zip(first, *others, strict=True)]


def _mark_arrays(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    rows = np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(len(column), -1)
    return np.ascontiguousarray(rows[:, : 2 * PLACES]).view(np.uint16), rows[:, 2 * PLACES :]


def _sets(texts: pa.Array) -> list[np.ndarray]:
    hashes = once_per_worker("word-hashes", WordHashes)
    return [shingles(t, hashes) for t in texts.cast(pa.binary()).to_pylist()]


def place_of(text: Column) -> Column:
    """A hash of the raw text: with the id it tells rows apart that share one of the two."""
    return F.xxhash64(text)


def sketches(docs: DataFrame, id_column: str, text_column: str) -> DataFrame:
    """(id, place, n, digest, bands) of every row; digest and bands are null for empty sets."""

    def sketch(batch: pa.RecordBatch) -> pa.RecordBatch:
        sets = _sets(batch.column(2))
        keys = bands(signatures(sets))
        digests = [xxhash.xxh3_128_digest(s.tobytes()) if s.size else None for s in sets]
        lists = pa.array([k.tolist() if s.size else None for k, s in zip(keys, sets, strict=True)], pa.list_(pa.int64()))
        columns = [batch.column(0), batch.column(1), pa.array([s.size for s in sets], pa.int64()), pa.array(digests, pa.binary()), lists]
        return pa.RecordBatch.from_arrays(columns, ["id", "place", "n", "digest", "bands"])

    text = filled(text_column)
    rows = docs.select(F.col(id_column).cast("long").alias("id"), place_of(text).alias("place"), text.alias("text"))
    return over_batches(rows, "id long, place long, n long, digest binary, bands array<long>", sketch)


def _full_sets(docs: DataFrame, wanted: DataFrame, id_column: str, text_column: str) -> DataFrame:
    """(node, n, keys, signature, shingles) of the rows (id, place, node) that stand for their nodes."""

    def full(batch: pa.RecordBatch) -> pa.RecordBatch:
        sets = _sets(batch.column(1))
        first = signatures(sets)
        columns = [pa.array([s.size for s in sets], pa.int64()), *(pa.array(x, pa.binary()) for x in ([k.tobytes() for k in bands(first)], marks(sets, first), [s.tobytes() for s in sets]))]
        return pa.RecordBatch.from_arrays([batch.column(0), *columns], ["node", "n", "keys", "signature", "shingles"])

    text = filled(text_column)
    rows = docs.select(F.col(id_column).cast("long").alias("id"), place_of(text).alias("place"), text.alias("text"))
    # one of the rows that repeat both id and text
    other = small(wanted.toDF("of_id", "of_place", "node"))
    chosen = rows.join(other, rows["id"].eqNullSafe(F.col("of_id")) & (rows["place"] == F.col("of_place"))).select("node", "text")
    return over_batches(chosen, "node long, n long, keys binary, signature binary, shingles binary", full)


def _estimated(pairs: DataFrame) -> DataFrame:
    """(a, b, estimate) of the pairs (a, b, sa, sb) whose estimate is likely."""

    def estimate(batch: pa.RecordBatch) -> pa.RecordBatch:
        (x, u), (y, v) = _mark_arrays(batch.column(2)), _mark_arrays(batch.column(3))
        share = ((x == y).sum(axis=1) + (u == v).sum(axis=1)) / ((1 + MORE) * PLACES)
        kept = batch.select(["a", "b"]).append_column("estimate", pa.array(share, pa.float64()))
        return kept.filter(pa.array(share >= LIKELY))

    return over_batches(pairs.select("a", "b", "sa", "sb"), "a long, b long, estimate double", estimate)


def _block_pairs(key: tuple, table: pa.Table) -> pa.Table:
    """Likely pairs (a, b), a < b, of different components in a block of a bucket, in the first band they share."""
    band, left, right = (key[i].as_py() for i in (1, 2, 3))
    ids, component, n, chunk = (table.column(c).to_numpy() for c in ("id", "component", "n", "chunk"))
    x, u = _mark_arrays(table.column("signature").combine_chunks())
    keys = np.frombuffer(b"".join(table.column("keys").to_pylist()), np.int64).reshape(len(ids), BANDS)
    found = []
    first = np.flatnonzero(chunk == left)
    second = np.flatnonzero(chunk == right)
    for k, i in enumerate(first):
        others = second[k + 1 :] if left == right else second
        others = others[(component[others] != component[i]) & (100 * np.minimum(n[others], n[i]) >= 75 * np.maximum(n[others], n[i]))]
        others = others[~(keys[others, :band] == keys[i, :band]).any(axis=1)]
        if not len(others):
            continue
        share = ((x[others] == x[i]).sum(axis=1) + (u[others] == u[i]).sum(axis=1)) / ((1 + MORE) * PLACES)
        found += [(min(ids[i], j), max(ids[i], j)) for j in ids[others[share >= LIKELY]]]
    return pa.table([pa.array([int(p[i]) for p in found], pa.int64()) for i in (0, 1)], ["a", "b"])


def _leftovers(open_members: DataFrame) -> DataFrame:
    """Likely pairs (a, b) of different components that share a bucket; rows have key, band, size, id, component, n, keys
    and signature."""
    chunks = F.ceil(F.col("size") / BLOCK).cast("int")
    rows = open_members.withColumn("chunk", F.pmod(F.xxhash64("id"), chunks).cast("int"))
    blocks = F.transform(F.sequence(F.lit(0), chunks - 1), lambda o: F.struct(F.least(o, F.col("chunk")).alias("left"), F.greatest(o, F.col("chunk")).alias("right")))
    rows = rows.withColumn("block", F.explode(blocks)).select("key", "band", "block.left", "block.right", "id", "component", "n", "chunk", "keys", "signature")
    return rows.groupBy("key", "band", "left", "right").applyInArrow(_block_pairs, "a long, b long").distinct()


def near_sizes(a: Column, b: Column) -> Column:
    """Whether sets of these sizes can reach the threshold at all."""
    return F.least(a, b) * 100 >= F.greatest(a, b) * 75


def _confirmed(pairs: DataFrame, full: DataFrame) -> DataFrame:
    """The pairs (a, b) whose full sets are similar enough."""

    def confirm(batch: pa.RecordBatch) -> pa.RecordBatch:
        keep = []
        for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
            x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
            common = len(np.intersect1d(x, y, assume_unique=True))
            keep.append(100 * common >= 75 * (len(x) + len(y) - common))
        return batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return over_batches(_with_both(pairs, full.select("node", "shingles"), ("x", "y")), "a long, b long", confirm)


def _with_both(pairs: DataFrame, sets: DataFrame, names: tuple[str, ...]) -> DataFrame:
    """pairs (a, b), a written table, with the columns of both nodes. A node of many pairs is dealt out, each part with a
    copy of its row."""
    half, total = len(names) // 2, pairs.count()
    of_b = cut(sizes_of(pairs, "b"), "hubs")
    hubs = sets.join(small(of_b.select(F.col("b").alias("node"))), "node", "left_semi").toDF("b", *names[half:])
    left = join_dealt(pairs, sets.toDF("a", *names[:half]), "a", "b", sizes_of(pairs, "a"), total)
    return join_dealt(left, hubs, "b", "a", of_b, total).select("a", "b", *names)


def _compared(pairs: DataFrame, full: DataFrame) -> DataFrame:
    """Pairs (a, b) with a likely estimate."""
    met = _with_both(pairs, full.select("node", "n", "signature"), ("na", "sa", "nb", "sb"))
    return _estimated(met.where(near_sizes(F.col("na"), F.col("nb"))))


def _nodes(rows: DataFrame) -> DataFrame:
    """(node, id, place, digest, bands) of every distinct set, written: nodes are numbered, and the row of smallest id
    stands for its set. Null ids come last."""
    first = F.min(F.struct(F.col("id").isNull().alias("none"), "id", "place")).alias("first")
    sets = rows.where("digest IS NOT NULL").groupBy("digest").agg(first, F.any_value("bands").alias("bands"))
    return cut(sets.select(F.monotonically_increasing_id().alias("node"), "first.id", "first.place", "digest", "bands"), "nodes")


def _buckets(keyed: DataFrame) -> DataFrame:
    """(key, size, copies) of the buckets of two or more rows of (id, band, key). Of buckets that have the same members, by
    count and 128 bits over their ids, the one of the first band stays, and copies is their number: every pair still
    meets in the first band that it shares."""
    both = (F.bit_xor(F.xxhash64("id", F.lit(seed))).alias(name) for seed, name in enumerate(("x", "y")))
    buckets = keyed.groupBy("key").agg(F.count("*").alias("size"), F.min("band").alias("band"), *both).where("size > 1")
    return buckets.groupBy("size", "x", "y").agg(F.min_by("key", "band").alias("key"), F.count("*").alias("copies")).select("key", "size", "copies")


def _members(nodes: DataFrame) -> DataFrame:
    """(key, band, size, copies, id) of the nodes in the buckets, written. Most keys have one node: they are counted and
    dropped before members are hashed. Both joins meet one row a key and are followed by no exchange, so Spark can
    split a key of many rows."""
    keyed = nodes.select(F.col("node").alias("id"), F.posexplode("bands").alias("band", "key"))
    shared = cut(sizes_of(keyed, "key").where("size > 1").select("key"), "shared")
    met = cut(keyed.join(shared, "key", "left_semi"), "met")
    chosen = cut(_buckets(met), "buckets")
    return cut(met.join(chosen, "key").select("key", "band", "size", "copies", "id"), "members")


def _node_labels(docs: DataFrame, nodes: DataFrame, id_column: str, text_column: str) -> DataFrame:
    """(id, component) of the nodes that have a link."""
    members = _members(nodes)
    salts = salts_of(F.col("size"))

    def of_bucket(left: DataFrame, right: DataFrame) -> DataFrame:
        """left with the row of right of its bucket."""
        return join_salted(left, right.withColumnRenamed("size", "its_size"), "key", "id", salts, salts_of(F.col("its_size"))).drop("its_size")

    wanted = nodes.join(members.select(F.col("id").alias("node")).distinct(), "node", "left_semi").select("id", "place", "node")
    full = cut(_full_sets(docs, wanted, id_column, text_column), "sets").dropDuplicates(["node"])
    # stars
    central = members.groupBy("id").agg(F.sum(F.col("size") * F.col("copies")).alias("weight"))
    hubs = members.join(central, "id").groupBy("key").agg(F.max_by("id", F.struct("weight", F.xxhash64("id"))).alias("hub"), F.first("size").alias("size"))
    spokes = cut(of_bucket(members, hubs).where("id <> hub").select(F.col("id").alias("a"), F.col("hub").alias("b")).distinct(), "spokes")
    tried = cut(_compared(spokes, full).groupBy("a").agg(F.max_by("b", "estimate").alias("b")), "stars")
    links = cut(_confirmed(tried, full), "links")
    labels = components(links)
    # leftovers
    named = members.join(labels, "id", "left").select("key", "band", "size", "id", F.coalesce("component", "id").alias("component"))
    named = cut(named, "named")
    mixed = named.groupBy("key").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.first("size").alias("size")).where("low <> high").select("key", "size")
    open_members = of_bucket(named, mixed).join(full.select(F.col("node").alias("id"), "n", "keys", "signature"), "id")
    failed = tried.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    rest = cut(_leftovers(open_members).join(failed, ["a", "b"], "left_anti"), "rest")
    more = cut(_confirmed(rest, full), "links")
    if more.isEmpty():
        return labels
    stars = labels.where("id <> component").toDF("a", "b")
    return components(stars.union(more))


def groups(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """(id, place, n, component) of every row of docs; component is the smallest id of the group."""
    rows = cut(sketches(docs, id_column, text_column), "sketches")
    nodes = _nodes(rows)
    labels = _node_labels(docs, nodes, id_column, text_column)
    linked = nodes.select(F.col("node").alias("id"), F.col("id").alias("low")).join(labels, "id")
    lowest = cut(linked.groupBy("component").agg(F.min("low").alias("low")), "lowest")
    labels = beside(labels, lowest, "component", "id").select(F.col("id").alias("node"), "low")
    named = cut(nodes.select("node", "id", "digest").join(labels, "node", "left").select("digest", F.coalesce("low", "id").alias("component")), "named")
    # rows of the most frequent sets are settled where they are read
    hot = F.broadcast(cut(frequent_digests(rows.where("digest IS NOT NULL")), "frequent"))
    rows = rows.select("id", "place", "n", "digest")
    heavy = rows.join(F.broadcast(named.join(hot, "digest", "left_semi")), "digest")
    rest = rows.where("digest IS NOT NULL").join(hot, "digest", "left_anti").join(named, "digest")
    empty = rows.where("digest IS NULL").withColumn("component", F.col("id"))
    out = ["id", "place", "n", "component"]
    return heavy.select(*out).unionByName(rest.select(*out)).unionByName(empty.select(*out))


def near_duplicates(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id and kept of every row of docs."""
    return groups(docs, id_column, text_column).select(
        F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.col("component").alias("component_id"), F.col("id").eqNullSafe(F.col("component")).alias("kept")
    )


def one_of_each(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """The rows of docs that have the smallest id of their group, with all their columns. Rows are told apart by id and
    text: of two texts under one id, one may go and the other stay."""
    lost = groups(docs, id_column, text_column).where(~F.col("id").eqNullSafe(F.col("component"))).select(F.col("id").alias("__lost"), F.col("place").alias("__place")).distinct()
    same = docs[id_column].cast("long").eqNullSafe(F.col("__lost")) & (place_of(filled(docs[text_column])) == F.col("__place"))
    return docs.join(lost, same, "left_anti")
