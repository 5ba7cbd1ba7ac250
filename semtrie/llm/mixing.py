"""Mixing sources to target weights by a Pfair schedule of blocks.

A source of weight ``w`` (of weights that sum to one) gives its k-th block the
release time ``floor((k - 1) / w)`` and the deadline ``ceil(k / w)``; earliest
deadline first fills every slot with one released block, so after any number of
slots each source has had its weight's share to within one block.  The weights
enter as whole numbers in the exact ratio of the given ones, so nothing is
rounded and no error adds up; the driver runs the schedule to its end, one step
per block, and every block finds its slot by one join.  On large tables blocks
grow, so that the driver never runs more than about ``max_slots`` steps.

Defined cases: a null source is a source of its own; rows of equal id keep their
number and are ordered by their other values (maps and variants, which have no
order, excepted); null and empty texts are rows like any other; an empty table gives an empty
schedule; a source with no target weight is left out of an explicit weight map
only by raising an error; other columns pass through (the four added names
replace columns of the same name).
"""

from __future__ import annotations

import heapq
from array import array
from collections.abc import Iterator
from fractions import Fraction
from itertools import islice
from math import lcm

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from semtrie.llm.common import small, table

BUCKETS = 1024
ADDED = ("mix_position", "mix_slot", "mix_block", "mix_epoch")


def exact_shares(weights: dict) -> dict[str, int]:
    """Whole numbers in the exact ratio of the weights."""
    if any(not w > 0 for w in weights.values()):
        raise ValueError("target weights must be positive")
    exact = {k: Fraction(w) for k, w in weights.items()}
    scale = lcm(*(x.denominator for x in exact.values()))
    return {k: int(x * scale) for k, x in exact.items()}


def integer_shares(weights: dict[str, float], cycle: int) -> dict[str, int]:
    """Shares of a cycle by largest remainder, at least one each; an approximation that ``mix_sources`` does not use."""
    if any(not w > 0 for w in weights.values()):
        raise ValueError("target weights must be positive")
    cycle = max(cycle, 4 * len(weights))
    total = sum(weights.values())
    exact = {k: w / total * cycle for k, w in weights.items()}
    shares = {k: max(1, int(x)) for k, x in exact.items()}
    order = sorted(exact, key=lambda k: (int(exact[k]) - exact[k], k))
    i = 0
    while sum(shares.values()) < cycle:
        shares[order[i % len(order)]] += 1
        i += 1
    while sum(shares.values()) > cycle:
        largest = max(shares, key=lambda k: (shares[k], k))
        shares[largest] -= 1
    return shares


def pfair_slots(shares: dict[str, int]) -> Iterator[tuple[str, int, int]]:
    """(source, k from 0, slot), slot by slot without end, by earliest deadline first among released blocks."""
    total = sum(shares.values())
    waiting = [(0, -(-total // a), s, 0) for s, a in shares.items()]
    heapq.heapify(waiting)
    ready: list[tuple[int, str, int]] = []
    slot = 0
    while True:
        while waiting and waiting[0][0] <= slot:
            _, deadline, s, k = heapq.heappop(waiting)
            heapq.heappush(ready, (deadline, s, k))
        _, s, k = heapq.heappop(ready)
        yield s, k, slot
        a = shares[s]
        heapq.heappush(waiting, ((k + 1) * total // a, -(-(k + 2) * total // a), s, k + 1))
        slot += 1


def pfair_cycle(shares: dict[str, int]) -> list[tuple[str, int, int]]:
    """The slots after which the schedule repeats."""
    return list(islice(pfair_slots(shares), sum(shares.values())))


def deviation(schedule: list[tuple[str, int, int]], shares: dict[str, int]) -> float:
    """Largest difference in blocks between what a source has had and its share of the slots so far."""
    cycle, had, worst = sum(shares.values()), dict.fromkeys(shares, 0), 0.0
    for s, _, slot in sorted(schedule, key=lambda x: x[2]):
        had[s] += 1
        worst = max(worst, *(abs(had[x] - shares[x] * (slot + 1) / cycle) for x in shares))
    return worst


def mix_sources(
    docs: DataFrame,
    *,
    source_col: str = "source",
    id_col: str = "doc_id",
    weights: dict[str | None, float] | None = None,
    temperature: float = 0.5,
    block: int = 32,
    cycle: int = 1000,
    repeat: bool = True,
    max_sources: int = 20_000,
    max_slots: int = 2_000_000,
    seed: int = 0,
) -> DataFrame:
    """Give each document its place in the mixture: position, slot, block and epoch.

    ``weights`` are the target weights by source; without them a source of n
    documents weighs ``n ** temperature``.  Documents of a source come in a
    seeded hash order, ``block`` to a slot (more where the schedule would
    otherwise have more than ``max_slots`` slots); ``mix_block`` counts the blocks of a
    source.  With ``repeat`` the schedule runs
    until every source has been read once, and shorter sources start over (next
    epoch), so the weights hold to the last slot; without it each document
    occurs once and a source that is used up leaves its later slots empty.
    ``cycle`` is accepted for older callers and changes nothing.

    Ranks inside a source are local ranks in hash buckets plus bucket offsets,
    so no task orders a whole source.  The driver sees one row per source and
    two numbers per slot.
    """
    spark = docs.sparkSession
    base = docs.drop(*ADDED)
    key = F.when(F.col(source_col).isNull(), F.lit("n")).otherwise(F.concat(F.lit("s"), F.col(source_col).cast("string")))
    h = F.xxhash64(F.lit(seed), F.col(id_col))
    keyed = base.select("*", key.alias("__src"), F.pmod(F.shiftrightunsigned(h, 40), F.lit(BUCKETS)).cast("int").alias("__bucket"), h.alias("__h"))

    counts = keyed.groupBy("__src", "__bucket").agg(F.count(F.lit(1)).alias("__n"))
    sizes = {r[0]: r[1] for r in counts.groupBy("__src").agg(F.sum("__n")).limit(max_sources + 1).collect()}
    if len(sizes) > max_sources:
        raise ValueError(f"more than {max_sources} sources")
    if weights is not None:
        given = {"n" if k is None else f"s{k}": w for k, w in weights.items()}
        if missing := sorted(set(sizes) - set(given)):
            raise ValueError(f"no target weight for {missing[:5]}")
        target = {k: given[k] for k in sizes}
    else:
        target = {k: n**temperature for k, n in sizes.items()}
    shares = exact_shares(target)
    # the schedule ends when the source that takes longest has been read once
    rows_to_come = max((n * sum(shares.values()) // shares[s] for s, n in sizes.items()), default=0)
    block = max(block, -(-rows_to_come // max_slots))
    number = {s: i for i, s in enumerate(sizes)}
    blocks = {s: -(-n // block) for s, n in sizes.items()}
    had = dict.fromkeys(sizes, 0)
    owners, turns, at = array("i"), array("q"), array("q")
    unread = len(sizes)
    for s, k, slot in pfair_slots(shares) if sizes else ():
        if repeat or k < blocks[s]:
            owners.append(number[s])
            turns.append(k)
            at.append(slot)
            had[s] = k + 1
        if k + 1 == blocks[s]:
            unread -= 1
            if not unread:
                break

    # with repeat a block runs on into the next epoch, so every slot is full
    rows = {s: had[s] * block if repeat else n for s, n in sizes.items()}
    plan = spark.createDataFrame([(s, number[s], n, rows[s]) for s, n in sizes.items()], "__src string, __number int, __size long, __rows long")
    slots = spark.createDataFrame(pa.table({"__number": pa.array(owners, pa.int32()), "__i": pa.array(turns, pa.int64()), "mix_slot": pa.array(at, pa.int64())}))

    before = Window.partitionBy("__src").orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.withColumn("__before", F.coalesce(F.sum("__n").over(before), F.lit(0))).drop("__n")
    local = Window.partitionBy("__src", "__bucket").orderBy("__h", id_col, *[F.col(c) for c in base.columns if c != id_col and not any(t in dict(base.dtypes)[c] for t in ("map<", "variant"))])
    ranked = keyed.withColumn("__local", F.row_number().over(local) - 1)
    # the plan is bounded by max_sources, so it may be broadcast
    placed = (
        ranked.join(offsets, ["__src", "__bucket"])
        .withColumn("__rank", F.col("__before") + F.col("__local"))
        .join(F.broadcast(plan), "__src")
        .withColumn("mix_epoch", F.explode(F.sequence(F.lit(0), F.expr("CAST((__rows - 1 - __rank) DIV __size AS INT)"))))
        .withColumn("__turn", F.col("__rank") + F.col("mix_epoch") * F.col("__size"))
        .withColumn("__i", F.expr(f"__turn DIV {block}"))
        .join(small(slots), ["__number", "__i"])
    )
    return placed.select(
        *base.columns,
        (F.col("mix_slot") * block + F.pmod("__turn", F.lit(block))).alias("mix_position"),
        "mix_slot",
        F.col("__i").alias("mix_block"),
        "mix_epoch",
    )


def op8_mix_sources(spark, sf_dir) -> DataFrame:
    """Query of operator 8 over all of ``documents``: each row's places in the mixture, epochs of short sources included."""
    return mix_sources(table(spark, sf_dir, "documents").select("doc_id", "source"))
