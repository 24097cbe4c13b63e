"""Block-wise planning for collections beyond memory: which blocks to load, and what to run on them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..session import cut
from . import planning
from .cutoff import choose_answer
from .execution import execute_plan
from .state import apply_outputs


@dataclass(frozen=True)
class BlockSettings:
    blocks: int
    capacity: int  # blocks that fit in memory
    load_cost: float
    d_max: int = 3


def make_blocks(state: DataFrame, n: int, exact: bool = True) -> DataFrame:
    """``object_id, block_id``: equal blocks by starting match probability, best first.

    The exact form ranks all objects in one window and suits small inputs; the other takes the edges from
    approximate quantiles, which sort nothing, and balances blocks up to their error.
    """
    if exact:
        return state.select("object_id", (F.ntile(n).over(W.orderBy(F.floor(F.col("match_p") * 1e9).desc(), "object_id")) - 1).alias("block_id"))
    edges = state.approxQuantile("match_p", [k / n for k in range(1, n)], 0.1 / n)
    at = sum((F.when(F.col("match_p") <= F.lit(e), 1).otherwise(0) for e in edges), F.lit(0))
    return state.select("object_id", at.cast("int").alias("block_id"))


def block_benefit(items: DataFrame, blocks: DataFrame) -> DataFrame:
    """Sum of the benefits of a block's items; blocks without items have 0."""
    total = items.join(blocks, "object_id").groupBy("block_id").agg(F.sum("benefit").alias("benefit"), F.count("*").alias("items"))
    every = blocks.select("block_id").distinct()
    return every.join(total, "block_id", "left").select("block_id", F.coalesce("benefit", F.lit(0.0)).alias("benefit"), F.coalesce("items", F.lit(0)).cast("long").alias("items"))


def refresh_block_benefit(before: DataFrame, touched: DataFrame, items: DataFrame, blocks: DataFrame) -> DataFrame:
    """Only blocks with objects run in the last epoch are summed again."""
    ids = touched.select("object_id").distinct().join(blocks, "object_id").select("block_id").distinct()
    again = block_benefit(items, blocks).join(ids, "block_id", "left_semi")
    return before.join(ids, "block_id", "left_anti").unionByName(again)


def block_queues(benefits: DataFrame, resident: list[int]) -> DataFrame:
    """``place, block_id, queue``: resident blocks by rising benefit, the others by falling benefit."""
    here = F.col("block_id").isin(resident) if resident else F.lit(False)
    q = benefits.withColumn("queue", F.when(here, "memory").otherwise("disk"))
    key = F.when(F.col("queue") == "memory", 1).otherwise(-1) * F.floor(F.col("benefit") * 1e9)
    return q.withColumn("place", F.row_number().over(W.partitionBy("queue").orderBy(key, "block_id"))).select("queue", "place", "block_id", "benefit")


def resident_after(queues: DataFrame, d: int, capacity: int) -> list[int]:
    """Resident blocks once the d best on disk have replaced as many of the worst in memory; free room is
    filled before anything is written back. As many rows as blocks reach the driver."""
    rows = sorted(queues.collect(), key=lambda r: (r["queue"], r["place"]))
    memory, disk = [r["block_id"] for r in rows if r["queue"] == "memory"], [r["block_id"] for r in rows if r["queue"] == "disk"]
    come = disk[:d]
    out = max(0, len(memory) + len(come) - capacity)
    return memory[out:] + come


def plan_alternatives(items: DataFrame, blocks: DataFrame, queues: DataFrame, settings: BlockSettings, budget: float) -> DataFrame:
    """``d, total, items``: for each number of swapped blocks, the benefit that fits into what loading leaves.

    Items get a row for each alternative in which their block is resident; the running cost is within d.
    """
    n_mem = queues.where("queue = 'memory'").count()
    most = min(settings.d_max, settings.blocks - n_mem, settings.capacity)
    with_block = items.join(blocks, "object_id")
    sets = {d: resident_after(queues, d, settings.capacity) for d in range(most + 1)}
    cells = F.array(*[F.struct(F.lit(d).alias("d"), F.lit(float(budget - d * settings.load_cost)).alias("room"), (F.col("block_id").isin(ids) if ids else F.lit(False)).alias("here")) for d, ids in sets.items()])
    rows = with_block.select("object_id", "pred", "scorer", "cost", "benefit", "rank_key", F.inline(cells)).where("here")
    order = W.partitionBy("d").orderBy(F.desc("rank_key"), "object_id", "pred", "scorer").rowsBetween(W.unboundedPreceding, 0)
    fits = rows.withColumn("running", F.sum("cost").over(order)).where("running - cost < room")
    return fits.groupBy("d").agg(F.sum("benefit").alias("total"), F.count("*").alias("items"))


def choose_block_plan(alternatives: DataFrame) -> int:
    rows = alternatives.collect()
    return max(rows, key=lambda r: (r["total"], -r["d"]))["d"] if rows else 1


def block_curve(run, epochs: int, settings: BlockSettings) -> list[tuple]:
    """Curve of a run in which only resident blocks can be worked on and loading costs a part of the epoch.

    The planner swaps blocks by their benefit. Baselines: scorer-first goes through the blocks by starting
    benefit, one scorer after the other; object-first finishes the objects of a set of best blocks before
    the next; random loads random blocks.
    """
    query, state, s = run.query, run.state, run.settings
    blocks = cut(make_blocks(state, settings.blocks))
    answer = choose_answer(state, s.alpha, s.answer)
    out = [(s.approach, 0, 0.0, 0, answer.size, answer.expected_f, run._quality(answer, state))]
    resident: list[int] = []
    spent = 0.0
    for number in range(1, epochs + 1):
        items = cut(run.items(state, answer, number))
        if items.isEmpty() and s.approach == "progressive" and s.on_exhausted == "drain":
            run.drained = True
            items = cut(run.items(state, answer, number))
            run.drained = False
        if items.isEmpty():
            break
        if s.approach == "progressive":
            queues = cut(block_queues(block_benefit(items, blocks), resident))
            d = choose_block_plan(plan_alternatives(items, blocks, queues, settings, run.budget))
            resident = resident_after(queues, d, settings.capacity)
        else:
            before = set(resident)
            left = {r["block_id"] for r in items.join(blocks, "object_id").select("block_id").distinct().collect()}
            if s.approach == "scorer_first":  # the blocks of the next scorer's items, round and round
                order = sorted(left)
                at = ((number - 1) * settings.capacity) % max(1, len(order))
                resident = (order[at:] + order[:at])[: settings.capacity]
            elif s.approach == "object_first":  # stay until a block is finished
                resident = [b for b in resident if b in left]
                resident += [b for b in sorted(left) if b not in resident][: settings.capacity - len(resident)]
            else:
                shuffled = sorted(range(settings.blocks), key=lambda b: ((b * 7919 + number * 104729 + s.seed * 15485863) % 1000003, b))
                resident = shuffled[: settings.capacity]
            d = len(set(resident) - before)
        load = d * settings.load_cost
        here = items.join(blocks.where(F.col("block_id").isin(resident)) if resident else blocks.limit(0), "object_id")
        plan = cut(planning.select_plan(here, run.budget - load))
        n, cost = plan.agg(F.count("*"), F.sum("cost")).first()
        if n:
            state = cut(apply_outputs(state, execute_plan(plan, run.objects, query, n), query))
        spent += (cost or 0.0) + load
        answer = choose_answer(state, s.alpha, s.answer)
        out.append((s.approach, number, float(spent), n, answer.size, answer.expected_f, run._quality(answer, state)))
    return out
