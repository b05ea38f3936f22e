"""N-gram Jaccard join by chosen paths.

A set takes part in a tree node by a hash of the node and each of its shingles: it enters the child of a shingle with
chance 1 / (SPLIT x size), so similar sets of like size meet with a chance that does not fall with depth, while others
part. Nodes with at most BUCKET sets are compared whole. Larger ones whose sets look alike (bottom sketches) are compared
too, because their pairs are results; the others split again up to DEPTH. Whatever is still large then is compared in
blocks, so no bucket is cut off. ``runs_for`` gives the number of independent trees for a target recall.

Only sketches, node numbers and keys are stored; shingle sets are taken from the texts where they are needed. A pair
belongs to the least node in which both of its sets are, so it is counted once although no list of pairs exists: a block
of a node first finds the sets that have a likely partner there (a sketch bound five standard errors below the
threshold), then their texts travel to the block, all pairs of which are verified exactly. A block gives the number of
links of each set and a local component of its links, not the pairs.

Cases: a text with fewer than WORDS words is one shingle of all its words; texts without words form one class; rows whose
shingle sets are equal are one class, not a quadratic number of pairs; a null doc_id takes part by its row but is never
a representative unless all of its class are null; an empty table gives no rows; other columns are kept by ``keep_one``,
whatever their names; of rows equal in doc_id and text it keeps one.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import connected_components
from .common import Words, chunks, forget, lists_of, mix, spill, whole_groups

WORDS = 5
THRESHOLD = 0.8
#: A child takes a shingle with chance 1 / (SPLIT x size).
SPLIT = 0.5
RECALL = 0.9999
DEPTH = 5
BUCKET = 256
#: Mean share of sets that hold a bucket's most common sketch values, above which the bucket is compared, not split.
ALIKE = 0.5
SKETCH = 32
#: Sets of one side of a comparison.
BLOCK = 1024
TOLD = "h bigint, c bigint, doc_id bigint, cid bigint, size int, sketch array<int>, nodes array<bigint>"


def runs_for(recall: float = RECALL, threshold: float = THRESHOLD, depth: int = DEPTH) -> int:
    """Trees needed so that a pair at the threshold meets in one of them with the chance ``recall``, at full depth."""
    miss = 0.0
    for _ in range(depth):
        miss = math.exp(threshold / SPLIT * (miss - 1))
    return math.ceil(math.log(1 - recall) / math.log(miss))


def shingle_sets(texts: list[str | None], k: int = WORDS) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text."""
    w = Words(texts)
    h, _, doc = w.windows(k)
    n, counts = len(texts), w.counts()
    cut = np.searchsorted(doc, np.arange(n + 1))
    out = []
    for i in range(n):
        part = h[cut[i] : cut[i + 1]]
        if not len(part) and counts[i]:
            with np.errstate(over="ignore"):
                x = np.full(1, counts[i], np.uint64)
                for v in w.hash[w.first[i] : w.first[i + 1]]:
                    x = mix(x * np.uint64(0xD6E8FEB86659FD93) + v)
            part = x
        out.append(np.unique(part.view(np.int64)))
    return out


def _texts(docs: DataFrame) -> DataFrame:
    """(h, c, text), the last one never null."""
    text = F.coalesce("text", F.lit(""))
    return docs.select(F.xxhash64(text).alias("h"), F.crc32(text).alias("c"), text.alias("text"))


def _list_array(parts: list[np.ndarray], kind):
    import pyarrow as pa

    flat = np.concatenate(parts) if parts else np.zeros(0)
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum([len(x) for x in parts])]).astype(np.int32)), pa.array(flat.astype(kind)))


def described(docs: DataFrame, runs: int) -> DataFrame:
    """(h, c, doc_id, cid, size, sketch, nodes) of each row: equal sets have equal cid; ``nodes`` are those of depth 1."""
    import pyarrow as pa

    def run(batches):
        for batch in batches:
            texts = batch.column("text").to_pylist()
            for a, b in chunks(texts):
                sets = shingle_sets(texts[a:b])
                with np.errstate(over="ignore"):
                    cid = [int(mix(np.array([mix(s.view(np.uint64)).sum(dtype=np.uint64) + np.uint64(len(s))], np.uint64)).view(np.int64)[0]) for s in sets]
                nodes = [np.unique(np.concatenate([_children(r, s) for r in range(1, runs + 1)])) if len(s) else s for s in sets]
                cols = [pa.array(cid, pa.int64()), pa.array([len(s) for s in sets], pa.int32()), _list_array([s[:SKETCH] >> 32 for s in sets], np.int32), _list_array(nodes, np.int64)]
                yield pa.RecordBatch.from_arrays([*(batch.column(k).slice(a, b - a) for k in ("h", "c", "doc_id")), *cols], ["h", "c", "doc_id", "cid", "size", "sketch", "nodes"])

    text = F.coalesce("text", F.lit(""))
    return docs.select(F.xxhash64(text).alias("h"), F.crc32(text).alias("c"), F.col("doc_id").cast("bigint").alias("doc_id"), text.alias("text")).mapInArrow(run, TOLD)


def _children(node: int, shingles: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = mix(shingles.view(np.uint64) ^ mix(np.full(1, node, np.int64).view(np.uint64) + np.uint64(0x9E3779B97F4A7C15)))
    take = x.astype(np.float64) < 2.0**64 / (SPLIT * len(shingles))
    with np.errstate(over="ignore"):
        return mix(x[take] + np.uint64(0xA0761D6478BD642F)).view(np.int64)


def _descend(rows: DataFrame) -> DataFrame:
    """(node, cid, low) of the children of each (cid, low, nodes, text) row."""
    import pyarrow as pa

    def run(batches):
        for batch in batches:
            texts, (nodes, edges) = batch.column("text").to_pylist(), lists_of(batch.column("nodes"))
            for a, b in chunks(texts):
                got = [np.unique(np.concatenate([_children(p, s) for p in nodes[edges[i] : edges[i + 1]].tolist()])) for i, s in enumerate(shingle_sets(texts[a:b]), a)]
                take = pa.array(np.repeat(np.arange(a, b), [len(x) for x in got]))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(got)), batch.column("cid").take(take), batch.column("low").take(take)], ["node", "cid", "low"])

    return rows.select("cid", "low", "nodes", "text").mapInArrow(run, "node bigint, cid bigint, low int")


def leaves(sets: DataFrame, texts: DataFrame) -> DataFrame:
    """(node, cid, blocks): the members of the nodes to compare, spilled."""
    low = F.get("sketch", F.lit(0)).alias("low")
    members = sets.select(F.explode("nodes").alias("node"), "cid", low)
    out, used, held = None, [], None
    for depth in range(1, DEPTH + 1):
        marks = members.groupBy("node", "low").agg(F.count("*").alias("n"))
        nodes = marks.groupBy("node").agg(F.sum("n").alias("n"), F.max("n").alias("most")).where("n > 1")
        stop = (F.col("n") <= BUCKET) | (F.col("most") >= ALIKE * F.col("n")) | F.lit(depth == DEPTH)
        nodes = spill(nodes.select("node", F.ceil(F.col("n") / BLOCK).cast("int").alias("blocks"), stop.alias("stop")))
        used += [nodes, members]
        found = members.join(nodes.where("stop"), "node").select("node", "cid", "blocks")
        out = found if out is None else out.unionByName(found)
        if depth == DEPTH or nodes.where("not stop").isEmpty():
            break
        deeper = members.join(nodes.where("not stop"), "node").groupBy("cid").agg(F.collect_set("node").alias("nodes"))
        if held is None:  # sets that go deeper later are among these: the texts of all are shuffled once
            held = spill(deeper.select("cid").join(sets.select("cid", low, "h", "c"), "cid").join(texts, ["h", "c"]).select("cid", "low", "text"))
        members = spill(_descend(deeper.join(held, "cid")))
    return spill(out, held, *used)


def sketch_pairs(size: np.ndarray, sketch: list[np.ndarray], threshold: float) -> np.ndarray:
    """Square of flags: pairs whose sizes and bottom sketches allow the threshold."""
    lens = np.fromiter(map(len, sketch), np.int64, len(sketch))
    common = shared_counts(sketch)
    # the largest value up to which a sketch knows its whole set
    whole = np.iinfo(np.int64).max
    reach = np.array([int(s[-1]) if n > len(s) else whole for s, n in zip(sketch, size, strict=True)])
    upto = np.stack([np.searchsorted(s, reach, "right") for s in sketch])
    known = np.maximum(upto + upto.T - common, 1)
    slack = np.where((reach[:, None] == whole) & (reach[None, :] == whole), 0, 5 * np.sqrt(threshold * (1 - threshold) / known))
    a = size.astype(np.float64)
    return (np.minimum(a[:, None], a[None, :]) >= threshold * np.maximum(a[:, None], a[None, :])) & (common >= (threshold - slack) * known) & (lens > 0)[:, None]


def shared_counts(sets: list[np.ndarray], columns: int = 8192) -> np.ndarray:
    """Sizes of the intersections of all pairs of sorted sets of distinct values."""
    n = len(sets)
    values, code = np.unique(np.concatenate(sets), return_inverse=True)
    owner = np.repeat(np.arange(n), [len(s) for s in sets])
    shared = np.bincount(code, minlength=len(values)) > 1
    keep = shared[code]
    owner, code = owner[keep], (np.cumsum(shared) - 1)[code[keep]]
    order = np.argsort(code, kind="stable")
    owner, code = owner[order], code[order]
    out = np.zeros((n, n), np.float32)
    for at in range(0, int(shared.sum()), columns):
        a, b = np.searchsorted(code, [at, at + columns])
        grid = np.zeros((n, min(columns, int(code[b - 1]) - at + 1)), np.float32)
        grid[owner[a:b], code[a:b] - at] = 1
        out += grid @ grid.T
    return out


def _owned(node: int, lists: list[np.ndarray], is_p: np.ndarray, is_q: np.ndarray) -> np.ndarray:
    """Square of flags: pairs of the two sides of a block that share no lesser node than ``node``."""
    lesser = [x[x < node] for x in lists]
    own = shared_counts(lesser) == 0 if sum(map(len, lesser)) else np.ones((len(lists), len(lists)), bool)
    own &= (is_p[:, None] & is_q[None, :]) | (is_q[:, None] & is_p[None, :])
    np.fill_diagonal(own, False)
    return own


BLOCK_KEY = ["node", "p", "q"]


def similar_sets(sets: DataFrame, texts: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(cid, others, root): rows that have links in one block each: copies of the linked sets, and a set that is linked
    with this one by way of links of that block. ``sets`` holds cid, h, c, size, sketch, nodes, copies."""
    import pyarrow as pa

    found = leaves(sets, texts)
    lists = found.groupBy("cid").agg(F.array_sort(F.collect_set("node")).alias("nodes"))
    block = F.pmod(F.xxhash64("cid", F.lit(7)), F.col("blocks")).cast("int")
    placed = found.withColumn("own", block).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    placed = placed.select("node", "cid", F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q"), (F.col("own") <= F.col("other")).alias("is_p"), (F.col("own") >= F.col("other")).alias("is_q"))
    mates = sets.select("cid", "size", "sketch").join(lists, "cid")
    rows = placed.join(mates, "cid").repartition(*BLOCK_KEY).sortWithinPartitions(*BLOCK_KEY)

    def likely(batches):
        for table, edges in whole_groups(batches, BLOCK_KEY):
            node, size, is_p, is_q = (np.asarray(table.column(c)) for c in ("node", "size", "is_p", "is_q"))
            (sk, at), (nodes, at_n) = lists_of(table.column("sketch")), lists_of(table.column("nodes"))
            keep = np.zeros(len(table), bool)
            for a, b in zip(edges[:-1], edges[1:], strict=True):
                if b - a < 2:
                    continue
                ok = sketch_pairs(size[a:b], [sk[at[x] : at[x + 1]] for x in range(a, b)], threshold)
                np.fill_diagonal(ok, False)
                if ok.any():
                    ok &= _owned(node[a], [nodes[at_n[x] : at_n[x + 1]] for x in range(a, b)], is_p[a:b], is_q[a:b])
                    keep[a:b] = ok.any(axis=1)
            if keep.any():
                yield from table.select([*BLOCK_KEY, "cid", "is_p", "is_q", "nodes"]).filter(pa.array(keep)).combine_chunks().to_batches()

    asked = rows.select(*BLOCK_KEY, "cid", "is_p", "is_q", "size", "sketch", "nodes").mapInArrow(likely, "node bigint, p int, q int, cid bigint, is_p boolean, is_q boolean, nodes array<bigint>")
    asked = spill(asked, found)
    full = asked.join(sets.select("cid", "h", "c", "copies"), "cid").join(texts, ["h", "c"])
    full = full.select(*BLOCK_KEY, "cid", "is_p", "is_q", "nodes", "copies", "text").repartition(*BLOCK_KEY).sortWithinPartitions(*BLOCK_KEY)

    def verify(batches):
        for table, edges in whole_groups(batches, BLOCK_KEY, weight="text"):
            node, cid, copies, is_p, is_q = (np.asarray(table.column(c)) for c in ("node", "cid", "copies", "is_p", "is_q"))
            nodes, at_n = lists_of(table.column("nodes"))
            out: list[list[np.ndarray]] = [[], [], []]
            for a, b in zip(edges[:-1], edges[1:], strict=True):
                have = shingle_sets(table.column("text").slice(a, b - a).to_pylist())
                size, common = np.array([len(s) for s in have], np.float64), shared_counts(have).astype(np.float64)
                ok = common / np.maximum(size[:, None] + size[None, :] - common, 1) >= threshold
                ok &= _owned(node[a], [nodes[at_n[x] : at_n[x + 1]] for x in range(a, b)], is_p[a:b], is_q[a:b])
                linked = np.flatnonzero(ok.any(axis=1))
                for o, x in zip(out, (cid[a:b][linked], (ok @ copies[a:b])[linked], _roots(ok, cid[a:b])[linked]), strict=True):
                    o.append(x)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(o).astype(np.int64)) for o in out], ["cid", "others", "root"])

    return full.mapInArrow(verify, "cid bigint, others bigint, root bigint")


def _roots(links: np.ndarray, name: np.ndarray) -> np.ndarray:
    """The least name in the component of each node of a small graph."""
    root = name.copy()
    far = np.iinfo(np.int64).max
    while True:
        new = np.minimum(root, np.where(links, root[None, :], far).min(axis=1))
        if (new == root).all():
            return root
        root = new


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD, recall: float = RECALL) -> tuple[DataFrame, DataFrame]:
    """(one row for each row: h, c, doc_id, comp, class_id, copy_id, n_links; links between copy classes that join them).

    comp names the component. class_id is its least doc_id, or comp where all doc_ids are null or another component has
    the same least doc_id; copy_id is the least doc_id of the rows with an equal set; n_links counts all other rows that
    are similar, copies included.
    """
    told = spill(described(docs, runs_for(recall, threshold)))
    key = F.min(F.struct("h", "c"))
    first = [F.first(c).alias(c) for c in ("size", "sketch", "nodes")]
    sets = spill(told.groupBy("cid").agg(key.alias("key"), *first, F.count("*").alias("copies"), F.min("doc_id").alias("copy_id")).select("cid", "key.h", "key.c", "size", "sketch", "nodes", "copies", "copy_id"))
    texts = _texts(docs).dropDuplicates(["h", "c"])
    links = spill(similar_sets(sets.where("size > 0"), texts, threshold))
    joins = links.where("cid <> root").select(F.col("cid").alias("src"), F.col("root").alias("dst")).distinct()
    parts = connected_components(joins).select(F.col("vid").alias("cid"), "comp")
    other = links.groupBy("cid").agg(F.sum("others").alias("others"))
    classes = sets.select("cid", "copies", "copy_id")
    known = classes.join(parts, "cid", "left").join(other, "cid", "left").withColumn("comp", F.coalesce("comp", "cid"))
    lead = known.groupBy("comp").agg(F.min("copy_id").alias("least"))
    # a least doc_id that names one component alone stays its class_id
    sole = lead.where("least is not null").groupBy("least").agg(F.min("comp").alias("comp"), F.count("*").alias("n")).where("n = 1")
    lead = lead.select("comp").join(sole, "comp", "left").select("comp", F.coalesce("least", "comp").alias("class_id"))
    table = known.join(lead, "comp").select("cid", "comp", "class_id", "copy_id", (F.col("copies") - 1 + F.coalesce("others", F.lit(0))).alias("n_links"))
    rows = told.select("h", "c", "doc_id", "cid")
    return rows.join(table, "cid").select("h", "c", "doc_id", "comp", "class_id", "copy_id", "n_links"), joins


def op2_chosen_path_join(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))[0].select("doc_id", "class_id", "copy_id", "n_links")


def keep_one(docs: DataFrame) -> DataFrame:
    """One document of each component of near-duplicates, with all its columns: the least doc_id, then the least text key."""
    found = near_duplicates(docs.select("doc_id", "text"))[0]
    best = found.groupBy("comp").agg(F.min(F.struct(F.col("doc_id").isNull().alias("nil"), "doc_id", "h", "c")).alias("k"))
    lead = best.select("k.doc_id", "k.h", "k.c")
    text = F.coalesce("text", F.lit(""))
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id").cast("bigint").alias("doc_id"), F.xxhash64(text).alias("h"), F.crc32(text).alias("c"))
    same = rows["doc_id"].eqNullSafe(lead["doc_id"]) & (rows["h"] == lead["h"]) & (rows["c"] == lead["c"])
    met = rows.join(lead, same, "left_semi")
    return met.dropDuplicates(["doc_id", "h", "c"]).select("row.*")
