"""Near duplicates by BagMinHash: weighted-Jaccard signatures of word-shingle multisets, banded, then verified.

An element's weight axis is cut into dyadic blocks (0,1], (1,2], (2,4], ...; each block carries a Poisson process
whose rate is its width.  A point has a time, a discretised weight level inside its block (the splitting of the
block's process into those of its levels) and a signature component; it counts if its level is within the
element's multiplicity, and a component's value is its earliest time.  Two bags agree in a component with
probability equal to their weighted Jaccard similarity, and points are drawn only while they can still come
before a bag's latest component.

Bags that are equal become one node first, named by its 128-bit key.  In each band bucket every node is held against
the bucket's centre, its least node.  These comparisons go in rounds: a node meets first the centre that it shares most
bands with, and later only centres whose class is still another than its own, so that what a round joins is linear
in the nodes.  Pairs of other members that are of two classes after that are compared in blocks of bounded size that
return only links which join classes.  So every pair that shares a band is decided by its exact multiset overlap or
already in one class.  The chance that a pair at the threshold shares no band is (1 - 0.8**4)**20, under 3 in 100,000.

Defined results: texts of 1 to 4 words are one shingle; a text without words is a class of its own, as is a row
with a null id; rows that repeat an id are told apart by their texts.  The class id is the least doc_id of the class.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .components import components
from .tables import discard, settle, table
from .textkit import U64, blocks, mix, releasing, segment_hash, words


@dataclass(frozen=True)
class NearDupParams:
    words: int = 5
    similarity: float = 0.8
    bands: int = 20
    rows: int = 4
    block: int = 400  #: documents of a block in the comparisons that stay open

    @property
    def components(self) -> int:
        return self.bands * self.rows


def shingles(data: np.ndarray, offsets: np.ndarray, n: int):
    """(key, doc) of every run of n words; of all its words, where a text has fewer."""
    seg = words(data, offsets)
    h = segment_hash(data, seg)
    per = seg.per_doc()
    first = np.concatenate([[0], np.cumsum(per)])[:-1]
    short = np.flatnonzero((per > 0) & (per < n))
    keys, docs = [], []
    if len(h) >= n:
        inside = np.flatnonzero(seg.doc[n - 1 :] == seg.doc[: len(h) - n + 1])
        g = np.full(len(inside), n, np.uint64)
        for i in range(n):
            g = mix(g * U64(0x9DDFEA08EB382D69) + h[inside + i])
        keys.append(g)
        docs.append(seg.doc[inside])
    for d in short:
        g = np.full(1, per[d], np.uint64)
        for i in range(per[d]):
            g = mix(g * U64(0x9DDFEA08EB382D69) + h[first[d] + i : first[d] + i + 1])
        keys.append(g)
        docs.append(np.array([d]))
    if not keys:
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    return np.concatenate(keys), np.concatenate(docs)


def bags(keys: np.ndarray, doc: np.ndarray):
    """(doc, key, weight) of the distinct shingles of each document, by document and key."""
    order = np.lexsort((keys, doc))
    k, d = keys[order], doc[order]
    edge = np.flatnonzero(np.concatenate([[True], (k[1:] != k[:-1]) | (d[1:] != d[:-1])])) if len(k) else np.empty(0, np.int64)
    return d[edge], k[edge], np.diff(np.concatenate([edge, [len(k)]])) if len(k) else edge


def bag_minhash(doc: np.ndarray, key: np.ndarray, weight: np.ndarray, n_docs: int, m: int) -> np.ndarray:
    """n_docs x m earliest times; inf for a document without elements."""
    top = np.where(weight > 1, np.ceil(np.log2(np.maximum(weight, 1))), 0).astype(np.int64)
    unit = np.repeat(np.arange(len(doc)), top + 1)
    block = np.arange(len(unit)) - np.repeat(np.concatenate([[0], np.cumsum(top + 1)])[:-1], top + 1)
    d, w = doc[unit], weight[unit]
    low = np.where(block > 0, 1 << np.maximum(block - 1, 0), 0)
    width = np.where(block > 0, low, 1)
    seed = mix(key[unit] + block.astype(np.uint64) * U64(0xA24BAED4963EE407))
    t = np.zeros(len(unit))
    out = np.full(n_docs * m, np.inf)
    turn = 0
    while len(d):
        turn += 1
        r = mix(seed + U64((turn * 0x9FB21C651E98DF25) % 2**64))
        t = t - np.log1p(-(r >> U64(11)).astype(np.float64) / float(1 << 53)) / width
        r = mix(r ^ U64(0xD1B54A32D192ED03))
        part = ((r >> U64(32)) * U64(m) >> U64(32)).astype(np.int64)
        level = low + 1 + ((r & U64(0xFFFFFFFF)) * width.astype(np.uint64) >> U64(32)).astype(np.int64)
        ok = level <= w
        np.minimum.at(out, d[ok] * m + part[ok], t[ok])
        latest = out.reshape(n_docs, m).max(1)
        go = t < latest[d]
        d, w, low, width, seed, t = d[go], w[go], low[go], width[go], seed[go], t[go]
    return out.reshape(n_docs, m)


def band_keys(signature: np.ndarray, params: NearDupParams) -> np.ndarray:
    bits = np.ascontiguousarray(signature).view(np.uint64).reshape(len(signature), params.bands, params.rows)
    h = np.full(bits.shape[:2], 1, np.uint64)
    for i in range(params.rows):
        h = mix(h * U64(0x9DDFEA08EB382D69) + bits[:, :, i])
    return h.view(np.int64)


def bag_keys(doc: np.ndarray, key: np.ndarray, weight: np.ndarray, n_docs: int) -> pa.Array:
    """The 128-bit key of each document's bag; null where it has no shingle."""
    halves = np.zeros((n_docs, 2), np.uint64)
    full, start = np.unique(doc, return_index=True)
    if len(full):
        for i, salt in enumerate((0x1, 0x5851F42D4C957F2D)):
            halves[full, i] = np.add.reduceat(mix(mix(key ^ U64(salt)) + weight.astype(np.uint64) * U64(0x9E3779B97F4A7C15)), start)
    none = np.ones(n_docs, bool)
    none[full] = False
    raw = halves.tobytes()
    return pa.array([None if none[i] else raw[16 * i : 16 * i + 16] for i in range(n_docs)], pa.binary())


def signatures(documents: DataFrame, params: NearDupParams) -> DataFrame:
    """doc_id, node (the key of the bag), bands (its band keys, null without a node); a null id has no node either."""

    def sign(batches):
        for rows, data, offsets in blocks(batches):
            n, m = rows.num_rows, params.bands
            d, k, w = bags(*shingles(data, offsets, params.words))
            node = bag_keys(d, k, w, n)
            band = band_keys(bag_minhash(d, k, w, n, params.components), params)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, n * m + 1, m), pa.int32()), pa.array(band.ravel()))
            none = pa.compute.or_(pa.compute.is_null(node), pa.compute.is_null(rows.column(0)))
            node, lists = (pa.compute.if_else(none, pa.nulls(n, x.type), x) for x in (node, lists))
            yield pa.RecordBatch.from_arrays([rows.column(0), node, lists], names=["doc_id", "node", "bands"])

    return documents.mapInArrow(sign, "doc_id long, node binary, bands array<long>")


def with_nodes(rows: DataFrame, node: str, params: NearDupParams) -> DataFrame:
    """The rows as they are, and the key of each one's bag in the column `node`."""

    def spell(batches):
        for part, data, offsets in blocks(batches, "__text"):
            key = bag_keys(*bags(*shingles(data, offsets, params.words)), part.num_rows)
            yield pa.RecordBatch.from_arrays([*part.columns[:-1], key], names=[*part.schema.names[:-1], node])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema), f"`{node}` binary"])
    return rows.withColumn("__text", F.col("text").cast("string")).mapInArrow(spell, schema)


def bag_sets(documents: DataFrame, params: NearDupParams) -> DataFrame:
    """node, items: the bag as a set of (shingle, occurrence) keys."""

    def spell(batches):
        for rows, data, offsets in blocks(batches):
            d, k, w = bags(*shingles(data, offsets, params.words))
            at = np.repeat(np.arange(len(d)), w)
            turn = np.arange(len(at)) - np.repeat(np.concatenate([[0], np.cumsum(w)])[:-1], w) if len(d) else at
            items = mix(k[at] + turn.astype(np.uint64) * U64(0xA24BAED4963EE407)).view(np.int64)
            ends = np.concatenate([[0], np.cumsum(np.bincount(d[at], minlength=rows.num_rows))])
            node = bag_keys(d, k, w, rows.num_rows)
            yield pa.RecordBatch.from_arrays([node, pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(items))], names=["node", "items"])

    return documents.mapInArrow(spell, "node binary, items array<long>").where("node is not null")


def verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs (a, b) with their exact multiset Jaccard similarity."""
    left = pairs.select("a", "b").join(sets.select(F.col("node").alias("b"), F.col("items").alias("items_b")), "b")
    both = left.join(sets.select(F.col("node").alias("a"), F.col("items").alias("items_a")), "a")
    shared = F.size(F.array_intersect("items_a", "items_b"))
    return both.select("a", "b", (shared / (F.size("items_a") + F.size("items_b") - shared)).alias("similarity"))


def labelled(df: DataFrame, column: str, labels: DataFrame, name: str) -> DataFrame:
    """df with the class of the node in `column`; a node without links is its own class."""
    known = labels.select(F.col("id").alias(column), F.col("label").alias(name))
    return df.join(known, column, "left").withColumn(name, F.coalesce(name, column))


def extended(labels: DataFrame, links: DataFrame) -> DataFrame:
    """The classes after more links: components over classes, so the work is that of the new links."""
    ends = labelled(labelled(links.select("a", "b"), "a", labels, "la"), "b", labels, "lb").where("la <> lb")
    joined = components(ends.select(F.col("la").alias("a"), F.col("lb").alias("b")))
    moved = labelled(labels.withColumnRenamed("label", "old"), "old", joined, "label").select("id", "label")
    out = settle(moved.union(joined.join(labels, "id", "left_anti").select("id", "label")), "labels")
    discard(joined)
    discard(labels)
    return out


def centre_links(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The classes (id, label) that the pairs (a, b, n) of centres and members make, tested in a few rounds.

    A round takes 1, then 2, 4, 8, ... of a member's open pairs, those of most common bands first, and drops pairs whose
    ends have come into one class by then.  The first round, of one pair a member, decides nearly all.
    """
    labels, few = None, 1
    while True:
        turn = F.row_number().over(Window.partitionBy("b").orderBy(F.desc("n"), "a"))
        ranked = settle(pairs.withColumn("turn", turn), "ranked")
        links = settle(verified(ranked.where(F.col("turn") <= few), sets).where(F.col("similarity") >= similarity).select("a", "b"), "links")
        labels = settle(components(links), "labels") if labels is None else extended(labels, links)
        left = labelled(labelled(ranked.where(F.col("turn") > few).drop("turn"), "a", labels, "la"), "b", labels, "lb")
        pairs = settle(left.where("la <> lb").select("a", "b", "n"), "pairs")
        discard(ranked)
        discard(links)
        if not pairs.limit(1).count():
            discard(pairs)
            return labels
        few *= 2


def cross_links(group: pa.Table, similarity: float) -> pa.Table:
    """Links (a, b) that join classes, between the documents of a task's two blocks; no more than documents less one.

    One document at a time is held against all others through their shingles' posting lists.
    """
    ids, label = np.array(group["id"].to_pylist(), object), np.array(group["label"].to_pylist(), object)
    items = group["items"].combine_chunks()
    if isinstance(items, pa.ChunkedArray):
        items = pa.concat_arrays(items.chunks)
    flat, ends = items.flatten().to_numpy(), items.value_lengths().to_numpy().astype(np.int64)
    first = np.concatenate([[0], np.cumsum(ends)])
    owner = np.repeat(np.arange(len(ids)), ends)
    order = np.argsort(flat, kind="stable")
    posted, holder = flat[order], owner[order]
    low, high = np.searchsorted(posted, flat, "left"), np.searchsorted(posted, flat, "right")
    kinds, root = np.unique(label, return_inverse=True)
    parent = list(range(len(kinds)))

    def find(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    out = []
    asking = np.flatnonzero(group["side"].to_numpy() == 1)
    for x in asking:
        lo, hi = low[first[x] : first[x + 1]], high[first[x] : first[x + 1]]
        size = hi - lo
        place = np.arange(size.sum()) + np.repeat(lo - np.concatenate([[0], np.cumsum(size)])[:-1], size)
        shared = np.bincount(holder[place], minlength=len(ids))
        near = np.flatnonzero((shared >= similarity * (ends[x] + ends - shared)) & (label != label[x]))
        for y in near:
            a, b = find(root[x]), find(root[y])
            if a != b:
                parent[a] = b
                out.append((min(ids[x], ids[y]), max(ids[x], ids[y])))
    return pa.table({"a": pa.array([r[0] for r in out], pa.binary()), "b": pa.array([r[1] for r in out], pa.binary())})


def open_links(in_bucket: DataFrame, labels: DataFrame, sets: DataFrame, params: NearDupParams) -> DataFrame:
    """What the comparison with the centres leaves open: links between documents of different classes.

    Documents whose buckets chain together form a field.  In a field the most frequent class needs no comparison
    with itself, so the others are compared with each other and with it, block by block: a task holds two blocks
    of at most about `block` documents, whatever the size of the field, and returns links that join classes alone.
    """
    members = labelled(in_bucket, "b", labels, "label")
    # the centre itself has met every member, so a bucket is open only where other members are of two classes
    kinds = members.groupBy("band", "value").agg(F.min("label").alias("low"), F.max("label").alias("high"))
    mixed = settle(kinds.where("low <> high").select("band", "value"), "mixed")
    opened = settle(members.join(mixed, ["band", "value"]).select("a", "b", "label"), "open")
    fields = components(opened.select("a", "b").distinct())
    member = settle(opened.select(F.col("b").alias("id"), "label").distinct().join(fields.withColumnRenamed("label", "field"), "id"), "field-members")
    sizes = member.groupBy("field", "label").agg(F.count(F.lit(1)).alias("n"))
    top = settle(sizes.groupBy("field").agg(F.max(F.struct("n", "label")).alias("top"), F.sum("n").alias("all")).where("all > top.n").select("field", F.col("top.label").alias("main"), F.col("top.n").alias("n0"), (F.col("all") - F.col("top.n")).alias("n1")), "fields")
    placed = member.join(top, "field").withColumn("side", F.when(F.col("label") == F.col("main"), 0).otherwise(1))
    blocks_0 = F.ceil(F.col("n0") / params.block).cast("int")
    blocks_1 = F.ceil(F.col("n1") / params.block).cast("int")
    own = F.pmod(F.xxhash64("id"), F.when(F.col("side") == 0, blocks_0).otherwise(blocks_1)).cast("int")
    rivals = F.transform(F.sequence(F.lit(0), blocks_1 - 1), lambda j: F.struct(F.least(own, j).alias("i"), F.greatest(own, j).alias("j")))
    mains = F.transform(F.sequence(F.lit(0), blocks_0 - 1), lambda j: F.struct(own.alias("i"), (-1 - j).alias("j")))
    asked = F.transform(F.sequence(F.lit(0), blocks_1 - 1), lambda i: F.struct(i.alias("i"), (-1 - own).alias("j")))
    tasks = placed.withColumn("task", F.explode(F.when(F.col("side") == 1, F.concat(rivals, mains)).otherwise(asked))).select("field", F.col("task.i").alias("i"), F.col("task.j").alias("j"), "id", "label", "side")
    ready = tasks.join(sets.withColumnRenamed("node", "id"), "id")
    return settle(ready.groupBy("field", "i", "j").applyInArrow(releasing(lambda group: cross_links(group, params.similarity)), "a binary, b binary"), "open-links")


def classes(documents: DataFrame, params: NearDupParams) -> tuple[DataFrame, DataFrame]:
    """(doc_id, node) of every row; and of nodes in a class of several rows (node, class_id, keeper).

    The keeper is the node of the class's least id, the lesser one where two texts share that id.
    """
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sig = settle(signatures(docs, params), "signatures")
    known = sig.where("node is not null")
    nodes = settle(known.groupBy("node").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"), F.min("bands").alias("bands")), "nodes")
    buckets = nodes.select(F.col("node").alias("id"), F.posexplode("bands").alias("band", "value"))
    centres = settle(buckets.groupBy("band", "value").agg(F.min("id").alias("a"), F.count(F.lit(1)).alias("size")).where("size > 1").drop("size"), "centres")
    in_bucket = settle(buckets.join(centres, ["band", "value"]).select("band", "value", "a", F.col("id").alias("b")).where("a <> b"), "buckets")
    pairs = settle(in_bucket.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n")), "pairs")
    wanted = settle(pairs.select(F.col("a").alias("node")).union(pairs.select(F.col("b").alias("node"))).distinct(), "wanted")
    texts = settle(wanted.join(nodes, "node").select(F.col("rep").alias("doc_id")).distinct(), "texts")
    sets = settle(bag_sets(docs.join(texts, "doc_id", "left_semi"), params).groupBy("node").agg(F.min("items").alias("items")), "bags")
    labels = centre_links(pairs, sets, params.similarity)
    more = open_links(in_bucket, labels, sets, params)
    if more.limit(1).count():
        labels = extended(labels, more)
    linked = labels.withColumnRenamed("id", "node").join(nodes.select("node", "rep"), "node")
    first = linked.groupBy("label").agg(F.min(F.struct("rep", "node")).alias("first"))
    of_links = linked.join(first, "label").select("node", F.col("first.rep").alias("class_id"), F.col("first.node").alias("keeper"))
    alone = nodes.where("copies > 1").join(labels.select(F.col("id").alias("node")), "node", "left_anti")
    of_copies = alone.select("node", F.col("rep").alias("class_id"), F.col("node").alias("keeper"))
    found = settle(of_links.union(of_copies), "classes")
    for done in (nodes, centres, in_bucket, pairs, wanted, texts, sets, labels, more):
        discard(done)
    return sig.select("doc_id", "node"), found


def near_duplicates(documents: DataFrame, params: NearDupParams = NearDupParams()) -> DataFrame:
    """doc_id, class_id for every row of `documents`."""
    rows, members = classes(documents, params)
    return rows.join(members.select("node", "class_id"), "node", "left").select("doc_id", F.coalesce("class_id", "doc_id").alias("class_id"))


def deduplicate(documents: DataFrame, params: NearDupParams = NearDupParams()) -> DataFrame:
    """One row of each class, that of the least id; rows with a null id stay.

    Of rows that agree in id and bag of shingles the least one (spelt as JSON) stays.
    """
    rows, members = classes(documents, params)
    own = rows.where("doc_id is not null").join(members, "node", "left")
    stays = F.col("keeper").isNull() | ((F.col("doc_id") == F.col("class_id")) & (F.col("node") == F.col("keeper")))
    ids = settle(own.groupBy("doc_id").agg(F.count(F.lit(1)).alias("rows"), F.sum(stays.cast("int")).alias("kept")).where("rows > 1 or kept = 0"), "ids")
    # one plan at every size: what goes grows with the input, so it is never broadcast
    keep = documents.join(ids.select(F.col("doc_id").alias("__id")).hint("merge"), F.col("doc_id").cast("long") == F.col("__id"), "left_anti")
    twice = ids.where("rows > 1 and kept > 0").select(F.col("doc_id").alias("__id"))
    if not twice.limit(1).count():
        return keep
    again = with_nodes(documents.join(twice, F.col("doc_id").cast("long") == F.col("__id"), "left_semi"), "__node", params)
    first = members.select(F.col("node").alias("__node"), F.col("class_id").alias("__class"), F.col("keeper").alias("__keeper"))
    stays = F.col("__keeper").isNull() | ((F.col("doc_id").cast("long") == F.col("__class")) & (F.col("__node") == F.col("__keeper")))
    whole = F.struct(*(F.col(f"`{c}`") for c in documents.columns))
    least = again.join(first, "__node", "left").where(stays).groupBy("doc_id", "__node").agg(F.min_by(whole, F.to_json(whole)).alias("__row"))
    return keep.unionByName(least.select("__row.*"))


def op3_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
