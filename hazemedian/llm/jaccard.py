"""N-gram Jaccard self-join by rare-first prefix filtering.

1. A pass over the texts hashes every 5-word shingle (64 bits) and keeps each document's set size and digest.  Equal
   sets count as one node, by digest.  It also counts shingles in a fixed table of 2^20 counters, an upper bound of
   every shingle's document frequency, which only tells hot shingles, those that would make one group's task too large.
2. A second pass sends each set's shingles, packed, to the task of their key group, which counts how many nodes have
   each exactly; hot ones are spread by node and count as most frequent.  Shingles of one node leave, the others go on
   to the task of their node with the class of their frequency.
3. A node's task knows how many shingles it shares with any other.  Nodes that share fewer than 3/4 of their set link
   with none and leave.  The others order their sets by (class, hash), rarest first, and post the prefix: of two sets
   with Jaccard >= 3/4 the first n - ceil(3n/4) + 1 elements must meet.  Shingles that no other node has come first and
   need no posting, so a document of which more than a quarter is its own posts nothing.
4. Postings are joined with length filter (sizes within 3/4) and positional filter (elements left on both sides
   must suffice), in star rounds (`link_nodes`).  Each of their pairs is verified once, on the shared shingles of both: a suffix filter bounds the
   overlap from the sizes of eight ranges of the sorted hashes, then the intersection is counted in full.
5. Keys whose nodes are still in several components make clusters.  The sets of a cluster meet in tasks: a
   cluster is cut into blocks of BLOCK_BYTES, every two blocks meet once, small clusters share a task, and no pair becomes
   a row.  Intersections are counted by shared elements, and links that join two components come out.

This decides the components.  The join itself (`ngram_links`, and the numbers of links of `linked_components`)
then lets all different sets of a component meet in the same way, for links run inside components only.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import group_of, pack, packed, shared_places, sorted_runs, unpacked
from .common import LOWER, SPACE, Scratch, mix, narrow, row_sets, shingle_hashes, slices, span_hashes, text_buffer, tidy, word_spans
from .components import link_nodes

WORDS = 5
#: Similarity as a fraction of integers: SHARE / WHOLE.
SHARE, WHOLE = 75, 100
COUNTERS = 1 << 20
#: Class of hot shingles; others have eight times the logarithm (base 2) of the number of their nodes, below this.
HOT = 255
_CHUNK = 1 << 16
#: Shingles that a key group's task gets, in bytes; the larger, the longer the runs of a document in a block.
GROUP_BYTES = 16 << 20
#: Bytes of sets in a block of the join inside components.
BLOCK_BYTES = 2 << 20


def text_sets(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(shingle hash, row), ascending by row and hash, without repeats."""
    data, offsets = text_buffer(column)
    data = LOWER[data]
    starts, ends, rows = word_spans(data, offsets, ~SPACE)
    return row_sets(*shingle_hashes(span_hashes(data, starts, ends), rows, WORDS))


def set_digests(hashes: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, size, digest) of every set that isn't empty."""
    if not len(hashes):
        return rows, rows, rows
    first = np.flatnonzero(np.r_[True, rows[1:] != rows[:-1]])
    size = np.diff(np.r_[first, len(rows)])
    total = np.add.reduceat(mix(hashes ^ np.uint64(0x51F15EED)), first)
    return rows[first], size, mix(total + size.astype(np.uint64)).view(np.int64)


def _sizes_and_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    counts = np.zeros(COUNTERS, np.uint32)
    for batch in batches:
        for part in slices(batch):
            hashes, rows = text_sets(part.column("text"))
            counts += np.bincount((hashes & np.uint64(COUNTERS - 1)).astype(np.int64), minlength=COUNTERS).astype(np.uint32)
            sizes, digests = np.zeros((2, part.num_rows), np.int64)
            own, size, digest = set_digests(hashes, rows)
            sizes[own], digests[own] = size, digest
            yield pa.record_batch({"doc_id": part.column("doc_id"), "n": pa.array(sizes), "node": pa.array(digests), "counts": pa.nulls(part.num_rows, pa.binary())})
    yield _count_rows(counts, "n")


def _count_rows(counts: np.ndarray, name: str) -> pa.RecordBatch:
    at = [k for k in range(COUNTERS // _CHUNK) if counts[k * _CHUNK : (k + 1) * _CHUNK].any()]
    whole = {"doc_id": pa.nulls(len(at), pa.int64()), name: pa.array(at, pa.int64()), "node": pa.nulls(len(at), pa.int64()), "counts": pa.array([counts[k * _CHUNK : (k + 1) * _CHUNK].tobytes() for k in at], pa.binary())}
    return pa.record_batch(whole)


def _summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    counts = np.zeros(COUNTERS, np.uint32)
    for batch in batches:
        for k, block in zip(batch.column("n").to_pylist(), batch.column("counts").to_pylist(), strict=True):
            part = counts[k * _CHUNK : (k + 1) * _CHUNK]
            np.add(part, np.frombuffer(block, np.uint32), out=part)
    yield _count_rows(counts, "n")


_FIRST = "doc_id long, n long, node long, counts binary"


def frequency_table(rows: DataFrame) -> np.ndarray:
    """All tasks' counters added up, over a tree of streaming tasks; the driver gets the 4 MB of the sum."""
    rows = rows.where(F.col("counts").isNotNull())
    for width in (max(1, int(rows.count() ** 0.5) // 4), 1):
        rows = rows.repartition(width).mapInArrow(_summed, _FIRST)
    counts = np.zeros(COUNTERS, np.uint32)
    for row in rows.collect():
        counts[row["n"] * _CHUNK : (row["n"] + 1) * _CHUNK] += np.frombuffer(row["counts"], np.uint32)
    return counts


def set_elements(column: pa.Array, counts: np.ndarray, hot: int, groups: int) -> tuple[np.ndarray, ...]:
    """(group, node, set size, shingle) of every different set of a column; hot shingles go to groups below 0, by node."""
    hashes, rows = text_sets(column)
    own, size, digest = set_digests(hashes, rows)
    once = np.zeros(len(own), bool)
    once[np.unique(digest, return_index=True)[1]] = True
    keep = np.repeat(once, size)
    hashes, nodes, sizes = hashes[keep].view(np.int64), np.repeat(digest[once], size[once]), np.repeat(size[once], size[once])
    group = group_of(hashes, groups)
    often = counts[hashes & (COUNTERS - 1)] > hot
    group[often] = -1 - group_of(nodes[often], groups)
    return group, nodes, sizes.astype(np.int32), hashes


def shared_elements(groups: int):
    """The task of a key group: its shingles that several nodes have, packed for the tasks of their nodes."""

    def shared(table: pa.Table) -> pa.Table:
        runs, hashes = unpacked(table.column("block"), "<i8", once=True)
        if table.column("g")[0].as_py() >= 0:
            keep, of, count = shared_places(runs, hashes)
            order = np.argsort(of, kind="stable")
            hashes, of, classes = hashes[keep[order]], of[order], np.minimum(8 * np.log2(count[order]), HOT - 1).astype(np.uint8)
        else:
            of, classes = np.repeat(np.arange(len(runs), dtype=np.int32), runs["count"]), np.full(len(hashes), HOT, np.uint8)
        nodes = runs["node"][of]
        found = list(packed(group_of(nodes, groups), nodes, runs["n"][of], hashes, classes))
        return pa.Table.from_batches(found) if found else table.slice(0, 0)

    return shared


def prefixes(table: pa.Table) -> pa.Table:
    """The task of a group of nodes: (node, n, items, first, keys) of the nodes that share enough to link.

    items: all shared shingles, ascending; keys: those in the prefix, rarest first, whose first stands at place `first`.
    """
    runs, hashes, classes = unpacked(table.column("block"), "<i8", "u1")
    nodes, sizes = np.repeat(runs["node"], runs["count"]), np.repeat(runs["n"], runs["count"])
    order = np.lexsort((hashes.view(np.uint64), classes, nodes))
    order = order[sorted_runs(nodes[order], hashes[order])]
    nodes, sizes, hashes = nodes[order], sizes[order].astype(np.int64), hashes[order]
    cut = sorted_runs(nodes)
    n, count = sizes[cut], np.diff(np.r_[cut, len(nodes)])
    least = (SHARE * n + WHOLE - 1) // WHOLE
    first, prefix = n - count, n - least + 1
    keep = np.flatnonzero(count >= least)
    items = [np.sort(hashes[a : a + c].view(np.uint64)).tobytes() for a, c in zip(cut[keep].tolist(), count[keep].tolist(), strict=True)]
    keys = [hashes[a : a + max(p, 0)] for a, p in zip(cut[keep].tolist(), np.minimum(prefix - first, count)[keep].tolist(), strict=True)]
    return pa.table({"node": pa.array(nodes[cut[keep]]), "n": pa.array(n[keep]), "items": pa.array(items, pa.binary()), "first": pa.array(first[keep]), "keys": pa.array(keys, pa.list_(pa.int64()))})


def possible(n, pos, other_n, other_pos):
    """Length and positional filter at a shared element of two rare-first ordered sets."""
    least = F.ceil((n + other_n) * SHARE / (SHARE + WHOLE))
    most = F.least(pos, other_pos) + 1 + F.least(n - pos, other_n - other_pos) - 1
    return (F.least(n, other_n) * WHOLE >= F.greatest(n, other_n) * SHARE) & (most >= least)


def enough(a: np.ndarray, b: np.ndarray, n: int, m: int) -> bool:
    """Whether sets of n and m elements link, whose common elements are among the ascending a and b; the suffix filter first."""
    need = -(-SHARE * (n + m) // (SHARE + WHOLE))
    if min(len(a), len(b)) < need:
        return False
    pivots = a[len(a) // 8 :: max(1, len(a) // 8)]
    cuts = np.diff(np.r_[0, np.searchsorted(a, pivots), len(a)]), np.diff(np.r_[0, np.searchsorted(b, pivots), len(b)])
    if int(np.minimum(*cuts).sum()) < need:
        return False
    merged = np.concatenate((a, b))
    merged.sort()
    both = int((merged[1:] == merged[:-1]).sum())
    return WHOLE * both >= SHARE * (n + m - both)


def verified(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        left, right = batch.column("left"), batch.column("right")
        n, m = batch.column("n").to_pylist(), batch.column("m").to_pylist()
        keep = [enough(np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64), *z) for x, y, *z in zip(left, right, n, m, strict=True)]
        yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))


def verify_by(scratch: Scratch, sets: DataFrame):
    """Pairs (a, b) checked on the sets (node, n, items) of both ends."""

    def verify(pairs: DataFrame) -> DataFrame:
        left, right = (sets.select(F.col("node").alias(k), F.col("n").alias(size), F.col("items").alias(name)) for k, size, name in (("a", "n", "left"), ("b", "m", "right")))
        met = pairs.join(left, "a").join(right, "b").select("a", "b", "n", "m", "left", "right")
        return scratch.keep(met.mapInArrow(verified, "a long, b long"), "linked")

    return verify


def links_among(sets: list[np.ndarray], whole: np.ndarray, left: np.ndarray, right: np.ndarray, wanted=None) -> Iterator[tuple[int, np.ndarray]]:
    """(k, the linked sets among `right`) of each set k of `left`, itself left out; intersections are counted by shared elements.

    whole: the sizes of the sets, of which `sets` may leave out elements that are in no other; wanted(k): the sets that
    matter for k, asked when k's turn comes.
    """
    size = np.array([len(x) for x in sets])
    of = np.repeat(np.arange(len(sets)), size)
    names, key, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    order = np.argsort(key, kind="stable")
    rows, ends = of[order], np.cumsum(times)
    stops = np.cumsum(size)
    for k in left.tolist():
        among = right if wanted is None else right & wanted(k)
        if not among.any():
            continue
        own = key[stops[k] - size[k] : stops[k]]
        own = own[times[own] > 1]
        many = times[own]
        at = np.arange(many.sum()) + np.repeat(ends[own] - np.cumsum(many), many)
        both = np.bincount(rows[at], minlength=len(sets))
        linked = among & (WHOLE * both >= SHARE * (whole + whole[k] - both))
        linked[k] = False
        yield k, np.flatnonzero(linked)


def joining_links(table: pa.Table) -> pa.Table:
    """Links (a, b) of a task's sets that join two parts; sets of one part, also by links found so far, need none."""
    table = table.take(pa.array(np.lexsort((table.column("node").to_numpy(), table.column("label").to_numpy()))))
    nodes, whole, side = (table.column(c).to_numpy() for c in ("node", "n", "side"))
    sets = [np.frombuffer(x, np.uint64) for x in table.column("items").to_pylist()]
    _, label = np.unique(table.column("label").to_numpy(), return_inverse=True)
    _, part = np.unique(table.column("part").to_numpy(), return_inverse=True)
    found: list[tuple[int, int]] = []
    for cluster in range(int(label.max()) + 1 if len(label) else 0):
        own = np.flatnonzero(label == cluster)
        for left, right in ((2, 2), (0, 1)):
            one, other = side[own] == left, side[own] == right
            if not one.any() or not other.any() or len(np.unique(part[own])) < 2:
                continue
            for k, linked in links_among([sets[x] for x in own.tolist()], whole[own], np.flatnonzero(one), other, lambda k, own=own: part[own] != part[own[k]]):
                for j in linked.tolist():
                    if part[own[j]] != part[own[k]]:
                        found.append((own[k], own[j]))
                        part[part == part[own[j]]] = part[own[k]]
    ends = np.array(found, np.int64).reshape(-1, 2)
    return pa.table({"a": pa.array(nodes[ends[:, 0]]), "b": pa.array(nodes[ends[:, 1]])})


def _found_links(table: pa.Table) -> Iterator[tuple[np.ndarray, np.ndarray, int, np.ndarray]]:
    """(nodes, rows of each node, k, linked sets) of a task's sets: side 0 meets side 1, side 2 meets itself."""
    side = table.column("side").to_numpy()
    nodes, rows, whole = (table.column(c).to_numpy() for c in ("node", "rows", "n"))
    sets = [np.frombuffer(x, np.uint64) for x in table.column("items").to_pylist()]
    for left, right in ((side == 2, side == 2), (side == 0, side == 1), (side == 1, side == 0)):
        if left.any() and right.any():
            for k, linked in links_among(sets, whole, np.flatnonzero(left), right):
                yield nodes, rows, k, linked


def link_pairs(table: pa.Table) -> pa.Table:
    a, b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for nodes, _, k, linked in _found_links(table):
        b.append(nodes[linked][nodes[linked] > nodes[k]])
        a.append(np.full(len(b[-1]), nodes[k]))
    return pa.table({"a": pa.array(np.concatenate(a)), "b": pa.array(np.concatenate(b))})


def link_sums(table: pa.Table) -> pa.Table:
    """Rows that a node's linked nodes have in this task, so that a large group gives no row for each pair."""
    found = [(nodes[k], rows[linked].sum()) for nodes, rows, k, linked in _found_links(table) if len(linked)]
    return pa.table({"node": pa.array([x for x, _ in found], pa.int64()), "links": pa.array([x for _, x in found], pa.int64())})


def _meetings(scratch: Scratch, sized: DataFrame, sets: DataFrame, labels: DataFrame):
    """The sets of components grouped so that all pairs of a component's sets meet exactly once."""
    nodes = scratch.keep(sized.where("n > 0").groupBy("node").agg(F.count("*").alias("rows")).join(labels, "node"), "nodes")
    return _grouped(scratch, sets.select("node", "n", "items").join(nodes, "node"), "rows")


def _grouped(scratch: Scratch, sets: DataFrame, more: str):
    """(node, n, items, label, `more`) grouped into tasks so that all pairs of a label's sets meet exactly once."""
    held = scratch.keep(sets, "held")
    groups = held.groupBy("label").agg(F.count("*").alias("members"), F.sum(F.octet_length("items")).alias("total")).where("members > 1")
    groups = scratch.keep(groups.select("label", F.ceil(F.col("total") / BLOCK_BYTES).cast("int").alias("blocks"), "total"), "groups")
    small = groups.where("blocks = 1").agg(F.sum("total")).first()[0] or 0
    buckets = 1 + int(small // BLOCK_BYTES)
    held = held.join(narrow(groups.drop("total")), "label").withColumn("own", F.pmod(F.xxhash64("node"), "blocks").cast("int"))
    held = held.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    label = F.when(F.col("blocks") > 1, F.col("label")).otherwise(F.pmod(F.xxhash64("label"), F.lit(buckets)))
    side = F.when(F.col("own") == F.col("other"), 2).when(F.col("own") < F.col("other"), 0).otherwise(1)
    return held.select((F.col("blocks") > 1).alias("cut"), label.alias("g"), "label", F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q"), side.alias("side"), "node", more, "n", "items").groupBy("cut", "g", "p", "q")


def ngram_links(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(links(a, b), members(doc_id, n_shingles, node)): every pair of different sets that link, once with a < b, and
    the set (node, a 64-bit digest) of every row with words.  Rows with one node are equal and link too.
    Edge cases are as in `ngram_components`.
    """
    scratch, sized, sets, labels = _labelled(docs)
    return _meetings(scratch, sized, sets, labels).applyInArrow(tidy(link_pairs), "a long, b long"), sized.where("n > 0").select("doc_id", F.col("n").alias("n_shingles"), "node")


def linked_components(docs: DataFrame) -> DataFrame:
    """`ngram_components` with n_links: the other rows whose text links with the row's, equal ones included."""
    scratch, sized, sets, labels = _labelled(docs)
    sums = _meetings(scratch, sized, sets, labels).applyInArrow(tidy(link_sums), "node long, links long").groupBy("node").agg(F.sum("links").alias("links"))
    equal = sized.where("n > 0").groupBy("node").agg((F.count("*") - 1).alias("equal"))
    links = scratch.keep(equal.join(sums, "node", "left").select("node", (F.col("equal") + F.coalesce("links", F.lit(0))).alias("n_links")).where("n_links > 0"), "links")
    named = _named(scratch, sized, labels).join(narrow(links), "node", "left")
    return named.select("doc_id", "n_shingles", "component_id", F.when(F.col("n_shingles") > 0, F.coalesce("n_links", F.lit(0))).otherwise(0).cast("long").alias("n_links"))


def ngram_components(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id of every row of `docs(doc_id, text)`.

    Two texts link when 100 * intersection >= 75 * union of their sets of 5-word shingles (A-Z lower-cased,
    words between ASCII white space; with fewer words the whole sequence is the only shingle).  Null and
    wordless texts have an empty set and stay alone; repeated rows each give a row; rows with a null doc_id
    can't be named by a component and give none; an empty table gives no row; other columns are not read.
    Shingles are compared by 64-bit hashes.
    """
    scratch, sized, _, labels = _labelled(docs)
    return _named(scratch, sized, labels).select("doc_id", "n_shingles", "component_id")


def _named(scratch: Scratch, sized: DataFrame, labels: DataFrame) -> DataFrame:
    named = sized.join(narrow(labels), "node", "left").withColumn("label", F.when(F.col("n") > 0, F.coalesce("label", "node")))
    named = scratch.keep(named, "named")
    smallest = named.where("label is not null").groupBy("label").agg(F.min("doc_id").alias("component_id"), F.count("*").alias("rows")).where("rows > 1").drop("rows")
    smallest = scratch.keep(smallest, "smallest")
    return named.join(narrow(smallest), "label", "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"), "node")


def _labelled(docs: DataFrame) -> tuple[Scratch, DataFrame, DataFrame, DataFrame]:
    """(scratch, sized(doc_id, n, node), sets(node, n, items, ...) of the nodes that may link, labels(node, label) of those that do)."""
    spark = docs.sparkSession
    scratch = Scratch(spark)
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).where("doc_id is not null")
    first = scratch.keep(rows.mapInArrow(tidy(_sizes_and_counts), _FIRST), "sizes")
    sized = first.where(F.col("counts").isNull()).select("doc_id", "n", "node")
    counts = frequency_table(first)
    total = sized.agg(F.sum("n")).first()[0] or 0
    groups = max(1, int(total * 8 // GROUP_BYTES))
    hot = 4 * int(total // COUNTERS) + 4096
    sent = spark.sparkContext.broadcast(counts)

    def elements(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = sent.value
        yield from pack(set_elements(part.column("text"), table, hot, groups) for batch in batches for part in slices(batch))

    shared = rows.mapInArrow(tidy(elements), "g long, block binary").groupBy("g").applyInArrow(tidy(shared_elements(groups)), "g long, block binary")
    sets = shared.groupBy("g").applyInArrow(tidy(prefixes), "node long, n long, items binary, first long, keys array<long>")
    sets = scratch.keep(sets, "sets")
    postings = sets.select("node", "n", "first", F.posexplode("keys").alias("place", "key")).select("key", "node", "n", (F.col("first") + F.col("place")).alias("pos"))


    def finish(members: DataFrame) -> DataFrame:
        return _grouped(scratch, sets.select("node", "n", "items").join(members, "node"), "part").applyInArrow(tidy(joining_links), "a long, b long")

    return scratch, sized, sets, link_nodes(scratch, postings, possible, verify_by(scratch, sets), finish)
