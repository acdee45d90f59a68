"""Links between those that meet in slots, counted without a shuffle of the meetings."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peakgroups.functions.storage import materialize

#: Rows of the slots' lists that executors hold at a time, and meetings that a task counts.
SENT_ROWS, TASK_MEETINGS = 4_000_000, 2_000_000
#: Meetings that a task counts in arrays.
ARRAY_MEETINGS = 400_000_000


def meeting_links(rows: DataFrame, times: bool = False, where: str = "true", both: bool = False, sent: int = SENT_ROWS) -> DataFrame:
    """``src, dst, weight``: in how many of ``rows(slot, user)`` two users meet, ``src < dst``
    (all of ``src <> dst`` if ``both``); rows with a null are left out.

    With ``times``, rows have ``t0, t1`` and a meeting counts if ``where`` holds for them and
    the other's ``u0, u1``. Rows are dealt by user, who finds the lists of all slots, a part
    of the other users at a time; so all meetings of two users are counted where they are
    made, and the shuffle has one row of each user and slot.
    """
    more = ["t0", "t1"] if times else []
    rows = materialize(rows.select("slot", "user", *more).where("slot is not null and user is not null"), "meetings")
    n = rows.groupBy("slot").count().selectExpr("cast(count as double) as n").agg(F.sum("n"), F.sum(F.col("n") * F.col("n"))).first()
    tasks = max(1, min(20_000, round((n[1] or 0) / TASK_MEETINGS / (1 if both else 2))))
    slices = max(1, -int(-(n[0] or 0) // (sent / (3 if times else 1))))
    left = rows.select("slot", F.col("user").alias("src"), *more).repartition(tasks, "src")
    out = None
    for part in range(slices):
        others = rows.where(F.pmod(F.xxhash64("user"), F.lit(slices)) == part).selectExpr("slot", "struct(user as dst" + (", t0 as u0, t1 as u1" if times else "") + ") as x")
        lists = others.groupBy("slot").agg(F.collect_list("x").alias("xs"))
        met = left.join(F.broadcast(lists), "slot").select("src", "slot", *more, F.inline("xs")).where("src <> dst" if both else "src < dst").where(where)
        links = met.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("weight"))
        out = links if out is None else out.union(links)
    return out


def best_meetings(slots: DataFrame, w: int, sent: int = SENT_ROWS, most: int = ARRAY_MEETINGS) -> DataFrame | None:
    """``src, dst, weight`` of :func:`meeting_links` in both directions, of which only those with
    the largest gain in modularity of their ``src``, if that is not negative; or, where not
    all others are held at a time, the largest among those held. None if gains need over 63 bits.

    ``slots(slot, user, n)`` once for each user in a slot of ``n``, over 1; ``w`` the number of
    all meetings. A task has some users and, a part at a time, the others by slot; it counts
    one user's meetings in an array and scores them there, so none of them is a row.
    """
    rows = materialize(slots, "meetings")
    k = rows.groupBy("user").agg(F.sum(F.col("n").cast("double") - 1).alias("k"), F.count(F.lit(1)).alias("c"))
    held, met = rows.agg(F.count(F.lit(1)), F.sum(F.col("n").cast("double"))).first()
    if 2 * w * (k.agg(F.max("k")).first()[0] or 0) >= 2.0**62:
        return None
    slices = max(1, -(-held // sent))
    blocks = max(1, min(10_000, round((met or 0) / slices / most)))
    spread = lambda seed, of: F.pmod(F.xxhash64("user", F.lit(seed)), F.lit(of)).cast("int")

    def lists(name: str, of: int, other: str, others: int, right: bool) -> DataFrame:
        packed = rows.groupBy(spread(int(right), of).alias(name), "slot", "n").agg(F.collect_list("user").alias("users"))
        every = packed.withColumn(other, F.explode(F.sequence(F.lit(0), F.lit(others - 1))))
        return every.select((F.col("block") * slices + F.col("slice")).cast("int").alias("task"), F.lit(right).alias("right"), "slot", "n", "users")

    both = lists("block", blocks, "slice", slices, False).union(lists("slice", slices, "block", blocks, True))
    return both.repartitionById(blocks * slices, "task").mapInArrow(lambda batches: _best(batches, w), "src long, dst long, weight long")


def _best(batches, w: int):
    import numpy as np
    import pyarrow as pa

    sides: dict = {False: [], True: []}
    for b in batches:
        right = b["right"].to_numpy(zero_copy_only=False)
        for side, kept in sides.items():
            part = b.filter(pa.array(right == side))
            if part.num_rows:
                lists = part["users"]
                size = np.diff(lists.offsets.to_numpy())
                kept.append((np.repeat(part["slot"].to_numpy(), size), np.repeat(part["n"].to_numpy(), size), lists.flatten().to_numpy()))
    if not all(sides.values()):
        return
    (slot, n, user), (slots, ns, others) = ([np.concatenate(x) for x in zip(*sides[side])] for side in (False, True))
    sides.clear()
    order = np.argsort(slots, kind="stable")
    slots, ids = slots[order], np.unique(others)
    others = np.searchsorted(ids, others)
    k = np.bincount(others, ns - 1, len(ids)).astype(np.int64)
    others = others[order]
    order = np.argsort(user, kind="stable")
    slot, n, user = slot[order], n[order], user[order]
    begin, end = np.searchsorted(slots, slot), np.searchsorted(slots, slot, "right")
    del slots, ns, order
    first = np.flatnonzero(np.append(True, user[1:] != user[:-1]))
    me = np.searchsorted(ids, user[first])
    out, held = [], 0
    for i, (lo, hi) in enumerate(zip(first, np.append(first[1:], len(user)))):
        met = np.concatenate([others[a:b] for a, b in zip(begin[lo:hi], end[lo:hi])])
        if 8 * len(met) < len(ids):
            who, x = np.unique(met, return_counts=True)
        else:
            x = np.bincount(met, minlength=len(ids))
            who = None
        gain = 2 * w * x - int((n[lo:hi] - 1).sum()) * (k if who is None else k[who])
        gain[x == 0] = -1
        if me[i] < len(ids) and ids[me[i]] == user[lo]:
            gain[me[i] if who is None else who == me[i]] = -1
        peak = gain.max(initial=-1)
        if peak < 0:
            continue
        at = np.flatnonzero(gain == peak)
        out.append((np.full(len(at), user[lo]), ids[at if who is None else who[at]], x[at].astype(np.int64)))
        held += len(at)
        if held > 100_000:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out)], names=["src", "dst", "weight"])
            out, held = [], 0
    if out:
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out)], names=["src", "dst", "weight"])
