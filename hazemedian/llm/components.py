"""Distributed union-find, and exact linking of nodes that share keys without all pairs of a group.

`link_nodes` gets postings (key, node, n, pos): two nodes may be linked only if they share a key.  Rounds of
star candidates (every node of a key against one pivot of the key, another pivot each round) join most
members of large groups by few verified pairs; keys whose nodes all have one label need no further pair and
leave for good.  What is left are pairs that cross labels inside a key.  All of them are verified, so no link between
components is lost, while pairs inside a component, whose verification could change nothing, are never made: either the
nodes of clusters of open keys meet in tasks (`finish`), or, when they are few, the pairs are made as rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch

STAR_ROUNDS = 12
#: Star rounds before nodes meet in tasks.
FIRST_ROUNDS = 2
#: Crossing pairs a posting at which star rounds stop paying.
FEW_PAIRS = 4
#: Edges that a task contracts before they are shuffled by node.
EDGES_A_TASK = 1_000_000


def smallest_labels(a: np.ndarray, b: np.ndarray, label: np.ndarray) -> np.ndarray:
    """Smallest labels along the edges (a, b), with jumps to the label's label, until nothing changes."""
    while True:
        low, new = np.minimum(label[a], label[b]), label.copy()
        for ends in (a, b):
            np.minimum.at(new, ends, low)
            np.minimum.at(new, label[ends], low)
        new = new[new]
        if (new == label).all():
            return label
        label = new


def _contracted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A task's edges as stars: (v, m) of each node v and the smallest node m that it reaches by them."""
    held: list = []

    def stars() -> pa.RecordBatch:
        a, b = (np.concatenate(x) for x in zip(*held, strict=True))
        names, ends = np.unique(np.r_[a, b], return_inverse=True)
        label = smallest_labels(ends[: len(a)], ends[len(a) :], np.arange(len(names)))
        keep = np.flatnonzero(label != np.arange(len(names)))
        return pa.record_batch({"v": pa.array(names[keep]), "m": pa.array(names[label[keep]])})

    size = 0
    for batch in batches:
        held.append((batch.column("v").to_numpy(), batch.column("m").to_numpy()))
        size += batch.num_rows
        if size >= 2 * EDGES_A_TASK:
            yield stars()
            held, size = [], 0
    if size:
        yield stars()


def _are_stars(edges: DataFrame) -> bool:
    """Whether each v has one m, and no m has a smaller node itself."""
    ends = edges.select(F.col("v").alias("x"), "m").union(edges.select("m", F.lit(None).cast("long")))
    met = ends.groupBy("x").agg(F.min("m").alias("low"), F.max("m").alias("high"), F.max(F.col("m").isNull()).alias("centre"))
    return met.where((F.col("low") != F.col("high")) | (F.col("low").isNotNull() & F.col("centre"))).isEmpty()


def connected(scratch: Scratch, edges: DataFrame) -> DataFrame:
    """(node, label) of every node of `edges(a, b)`; label is the smallest node of the component.

    Tasks contract their own edges first.  Where these don't make stars already, two contractions alternate, each a grouped
    minimum and a join on nodes: larger neighbours move to a node's smallest neighbour, then smaller neighbours do;
    stars remain after a logarithmic number of rounds.
    """
    whole = scratch.keep(edges.select(F.greatest("a", "b").alias("v"), F.least("a", "b").alias("m")).where("v <> m"), "edges")
    tasks = -(-whole.count() // EDGES_A_TASK)
    now = scratch.keep(whole.repartition(max(1, tasks)).mapInArrow(_contracted, "v long, m long"), "edges")
    scratch.drop(whole)
    while not _are_stars(now):
        both = now.union(now.select(F.col("m").alias("v"), F.col("v").alias("m")))
        low = both.groupBy("v").agg(F.min("m").alias("low"))
        large = both.where("m > v").join(low, "v").select(F.col("m").alias("v"), F.least("low", "v").alias("m")).distinct()
        low = large.groupBy("v").agg(F.min("m").alias("low"))
        small = large.join(low, "v").where("m <> low").select(F.col("m").alias("v"), F.col("low").alias("m")).union(low).distinct()
        new = scratch.keep(small, "edges")
        scratch.drop(now)
        now = new
    return now.select(F.col("v").alias("node"), F.col("m").alias("label")).distinct().union(now.select("m", "m").distinct())


def link_nodes(scratch: Scratch, postings: DataFrame, possible: Callable[[Column, Column, Column, Column], Column], verify: Callable[[DataFrame], DataFrame], finish: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """(node, label) of the nodes of `postings(key, node, n, pos)` that are linked with another; label is the smallest node.

    possible(n, pos, other n, other pos) is a condition that every linked pair meets at each shared key;
    verify(pairs(a, b)) returns those that are linked, written to the shared folder; finish(members(node, part, label))
    gets the nodes of the keys that FIRST_ROUNDS left open, their component so far and their cluster, and returns links
    that join the parts of each cluster.
    """
    rounds = STAR_ROUNDS if finish is None else FIRST_ROUNDS
    open_, tested, linked, labels = postings, None, None, None
    for turn in range(rounds + 1):
        named = open_.withColumn("label", F.col("node")) if labels is None else open_.select("key", "node", "n", "pos").join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
        keys = named.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.min(F.struct(F.xxhash64("node", F.lit(turn)).alias("h"), "node", "n", "pos", "label")).alias("pivot")).where("lo <> hi").drop("lo", "hi")
        still = scratch.keep(named.join(keys, "key"), "open")
        if turn:
            scratch.drop(open_)
        open_ = still
        rows = open_.count()
        if not rows:
            break
        if finish is not None and turn == rounds:
            clusters = connected(scratch, open_.select(F.col("label").alias("a"), F.col("pivot.label").alias("b")))
            members = open_.select("node", F.col("label").alias("part")).distinct().join(clusters.withColumnRenamed("node", "part"), "part")
            found = scratch.keep(finish(members), "linked")
            linked = found if linked is None else linked.union(found)
            break
        by_label = open_.groupBy("key", "label").agg(F.count("*").alias("c"))
        crossing = 0 if finish is not None else by_label.groupBy("key").agg((F.sum("c") * F.sum("c") - F.sum(F.col("c") * F.col("c"))).cast("double").alias("x")).agg(F.sum("x") / 2).first()[0]
        last = finish is None and (turn == rounds or crossing <= FEW_PAIRS * rows)
        if last:
            a, b = (open_.select("key", *(F.col(c).alias(c + x) for c in ("label", "node", "n", "pos"))) for x in "ab")
            la, lb = (by_label.select("key", F.col("label").alias("label" + x)) for x in "ab")
            across = la.join(lb, (la["key"] == lb["key"]) & (F.col("labela") < F.col("labelb"))).select(la["key"], "labela", "labelb")
            met = across.join(a, ["key", "labela"]).join(b, ["key", "labelb"]).where(possible(F.col("na"), F.col("posa"), F.col("nb"), F.col("posb")))
            pairs = met.select(F.least("nodea", "nodeb").alias("a"), F.greatest("nodea", "nodeb").alias("b"))
        else:
            met = open_.where((F.col("label") != F.col("pivot.label")) & possible(F.col("n"), F.col("pos"), F.col("pivot.n"), F.col("pivot.pos")))
            pairs = met.select(F.least("node", "pivot.node").alias("a"), F.greatest("node", "pivot.node").alias("b"))
        pairs = pairs.distinct()
        if tested is not None:
            pairs = pairs.join(tested, ["a", "b"], "left_anti")
        pairs = scratch.keep(pairs, "pairs")
        tested = pairs if tested is None else tested.union(pairs)
        found = verify(pairs)
        linked = found if linked is None else linked.union(found)
        del named, keys, by_label
        if last:
            break
        labels = scratch.keep(connected(scratch, linked), "labels")
    if linked is None:
        return postings.select("node", F.col("node").alias("label")).limit(0)
    return scratch.keep(connected(scratch, linked), "labels")
