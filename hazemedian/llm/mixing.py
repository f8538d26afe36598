"""Mixing sources to target weights by temperature, realised as budgeted block permutations.

Weights are the sources' token shares (ids of the vocabulary that the token files use) to the power alpha, normalised.  alpha in [0, 1] is bisected to the largest value
whose weights reach a target entropy, then raised if a source would otherwise be repeated more than MOST_EPOCHS times.
Smaller alpha is flatter: entropy falls and the most repeated source's epochs fall as alpha grows, so both bounds are one-sided.

The budget (tokens of the whole mixture) is by default the smallest that takes every document at least once.
A source with budget b and t tokens is taken floor(b / t) times whole, and one more time in part: its
documents are dealt by a seeded hash to blocks, blocks and documents inside them stand in hashed order, another order each epoch, and the
part is the longest run of blocks whose tokens stay within the rest of the budget, and of the block after it the
documents, in order, that still fit, with one exchange of two that fills it best.  Sums of blocks decide which blocks are whole; only the block at the end is
summed document by document, so no task sees a source.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import ROW_KEY, Scratch, free_name, keyed, narrow
from .tokens import count_tokens

ENTROPY_SHARE = 0.97
MOST_EPOCHS = 2.0
BLOCK_DOCUMENTS = 256
SEED = 1


def weights_at(tokens: dict, alpha: float) -> dict:
    top = max(tokens.values())
    raised = {k: (v / top) ** alpha for k, v in tokens.items()}
    whole = sum(raised.values())
    return {k: v / whole for k, v in raised.items()}


def entropy(weights: dict) -> float:
    return -sum(w * math.log(w) for w in weights.values() if w > 0)


def epochs(tokens: dict, weights: dict, budget: float | None = None) -> dict:
    """Times that each source is taken; without a budget the least taken source is taken once."""
    per = {k: weights[k] / v for k, v in tokens.items()}
    budget = 1 / min(per.values()) if budget is None else budget
    return {k: budget * p for k, p in per.items()}


def bisect_alpha(tokens: dict, target_entropy: float | None = None, most_epochs: float = MOST_EPOCHS, budget: float | None = None, steps: int = 60) -> float:
    """The exponent: target entropy first (default ENTROPY_SHARE of the greatest), then the repetition limit."""

    def bisected(fits_low) -> float:
        """The largest alpha for which fits_low holds; it holds up to some alpha."""
        low, high = 0.0, 1.0
        if fits_low(high):
            return high
        for _ in range(steps):
            mid = (low + high) / 2
            low, high = (mid, high) if fits_low(mid) else (low, mid)
        return low

    goal = ENTROPY_SHARE * math.log(len(tokens)) if target_entropy is None else target_entropy
    alpha = bisected(lambda a: entropy(weights_at(tokens, a)) >= goal)
    repeats = bisected(lambda a: max(epochs(tokens, weights_at(tokens, a), budget).values()) > most_epochs)
    if max(epochs(tokens, weights_at(tokens, alpha), budget).values()) > most_epochs:
        alpha = repeats if repeats == 1.0 else min(1.0, repeats + 2.0 ** -(steps - 1))
    return alpha


def plan(docs: DataFrame, target_entropy: float | None = None, most_epochs: float = MOST_EPOCHS, budget: float | None = None, carried: tuple[str, ...] = ()) -> tuple[DataFrame, list[dict]]:
    """(doc_id, source, n_tokens of every row, written to the shared folder; the sources' figures).

    The figures are a row for each source with a token: tokens, share, weight, budget, epochs, alpha.
    """
    scratch = Scratch(docs.sparkSession)
    rows = docs.select("doc_id", "text", F.coalesce(F.col("source").cast("string"), F.lit("")).alias("source"), *carried)
    sized = scratch.keep(count_tokens(rows, carried=("source", *carried)).select("doc_id", "source", "n_tokens", *carried), "sized")
    found = sized.groupBy("source").agg(F.sum("n_tokens").alias("t")).where("t > 0").orderBy("source").collect()
    tokens = {x["source"]: float(x["t"]) for x in found}
    if not tokens:
        return sized, []
    alpha = bisect_alpha(tokens, target_entropy, most_epochs, budget)
    weights, whole = weights_at(tokens, alpha), sum(tokens.values())
    times = epochs(tokens, weights, budget)
    return sized, [{"source": k, "tokens": int(v), "share": v / whole, "weight": weights[k], "budget": int(times[k] * v + 1e-6), "epochs": times[k], "alpha": alpha} for k, v in tokens.items()]


def schedule(docs: DataFrame, target_entropy: float | None = None, most_epochs: float = MOST_EPOCHS, budget: float | None = None, seed: int = SEED) -> DataFrame:
    """doc_id, source, n_tokens, epoch (from 0), order_key of every document each time it is taken.

    Sorting by order_key inside an epoch gives the source's block permutation.  A null source is the source "";
    null and empty texts have no tokens and are taken with every whole epoch; documents without tokens of a source
    without tokens are taken once; rows with a null doc_id and repeated rows are rows like others; an empty table gives no row; other columns
    are not read.
    """
    return _scheduled(docs, target_entropy, most_epochs, budget, seed)


def _scheduled(docs: DataFrame, target_entropy: float | None = None, most_epochs: float = MOST_EPOCHS, budget: float | None = None, seed: int = SEED, carried: tuple[str, ...] = ()) -> DataFrame:
    """`schedule` with further columns of `docs`; the first of them orders the rows without a doc_id."""
    spark = docs.sparkSession
    scratch = Scratch(spark)
    sized, figures = plan(docs, target_entropy, most_epochs, budget, carried)
    name = F.coalesce("doc_id", *carried[:1])
    if not figures:
        return sized.select("doc_id", "source", "n_tokens", F.lit(0).alias("epoch"), F.xxhash64(name, F.lit(seed)).alias("order_key"), *carried)
    # One row a source.
    per = spark.createDataFrame([(x["source"], x["budget"] // x["tokens"], x["budget"] % x["tokens"]) for x in figures], "source string, whole long, rest long")
    count = sized.groupBy("source").agg(F.greatest(F.lit(1), F.ceil(F.count("*") / BLOCK_DOCUMENTS)).cast("long").alias("n_blocks"))
    rows = sized.join(narrow(scratch.keep(per.join(count, "source", "right"), "sources")), "source").withColumns({"whole": F.coalesce("whole", F.lit(1)), "rest": F.coalesce("rest", F.lit(0))})

    def key(epoch):
        return F.xxhash64(name, F.lit(seed), epoch)

    whole = rows.select("doc_id", "source", "n_tokens", *carried, F.explode(F.sequence(F.lit(0), F.greatest(F.col("whole"), F.lit(1)).cast("int") - 1)).alias("epoch"), "whole").where("epoch < whole")
    whole = whole.select("doc_id", "source", "n_tokens", "epoch", key(F.col("epoch")).alias("order_key"), *carried)

    part = rows.where("rest > 0").select("doc_id", "source", "n_tokens", *carried, "rest", F.col("whole").cast("int").alias("epoch"), "n_blocks")
    part = part.withColumn("order_key", key(F.col("epoch"))).withColumn("block", F.pmod(F.xxhash64(name, F.lit(seed + 7919), "epoch"), "n_blocks")).withColumn("block_key", F.xxhash64("block", F.lit(seed), "epoch"))
    sums = part.groupBy("source", "block", "block_key", "rest").agg(F.sum("n_tokens").alias("t"))
    # Running sums over blocks: first over runs of blocks with the same leading bits, then inside the runs.
    sums = sums.withColumn("run", F.shiftright("block_key", 52))
    runs = sums.groupBy("source", "run").agg(F.sum("t").alias("rt")).withColumn("run_before", F.sum("rt").over(Window.partitionBy("source").orderBy("run")) - F.col("rt")).drop("rt")
    inside = Window.partitionBy("source", "run").orderBy("block_key", "block")
    sums = sums.join(runs, ["source", "run"]).withColumn("before", F.sum("t").over(inside) - F.col("t") + F.col("run_before"))
    taken = scratch.keep(sums.where("before < rest").select("source", "block", "before", (F.col("before") + F.col("t") <= F.col("rest")).alias("all")), "blocks")
    held = part.join(taken, ["source", "block"])
    ends = held.where("not all")
    columns = ["doc_id", "source", "n_tokens", "epoch", "order_key", *carried]
    ends = ends.select(*columns, "block", (F.col("rest") - F.col("before")).alias("left"))

    def filled(table: pa.Table) -> pa.Table:
        """The documents of an end block, in order, that fit into what is left, and at last the one exchange of two that fills it best."""
        order = ["order_key", "doc_id", "n_tokens", *carried]
        table, taken = table.sort_by([(c, "ascending") for c in order]), []
        left = table.column("left")[0].as_py()
        for n in table.column("n_tokens").to_pylist():
            taken.append(n <= left)
            left -= n if taken[-1] else 0
        sizes, chosen = table.column("n_tokens").to_numpy(), np.array(taken)
        out, into = np.flatnonzero(chosen), np.flatnonzero(~chosen)
        if left and len(out) and len(into):
            into = into[np.argsort(sizes[into], kind="stable")]
            at = np.searchsorted(sizes[into], sizes[out] + left, side="right") - 1
            more = np.where(at >= 0, sizes[into[at]] - sizes[out], 0)
            if more.max() > 0:
                taken[out[more.argmax()]], taken[into[at[more.argmax()]]] = False, True
        return table.filter(pa.array(taken, pa.bool_())).select(columns)

    ends = ends.groupBy("source", "block").applyInArrow(filled, ends.select(columns).schema)
    return whole.unionByName(held.where("all").select(columns)).unionByName(ends.select(columns))


def mixed(docs: DataFrame, **options) -> DataFrame:
    """`docs` with every row as often as the schedule takes it, at least once if nothing limits the budget.

    Rows are told apart by a row_key, so that null and repeated doc_ids are rows like others; null sources are the source "";
    rows without tokens are taken as `schedule` says; an empty table stays empty; all columns stay, whatever their names.
    """
    rows = keyed(docs)
    times, turn = free_name(rows, "times"), free_name(rows, "turn")
    each = _scheduled(rows, **options, carried=(ROW_KEY,)).groupBy(ROW_KEY).agg(F.count("*").cast("int").alias(times))
    each = Scratch(docs.sparkSession).keep(each, "times")
    repeated = rows.join(narrow(each), ROW_KEY).withColumn(turn, F.explode(F.sequence(F.lit(1), F.col(times))))
    return repeated.select(docs.columns)
