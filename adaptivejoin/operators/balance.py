"""How many calls of a batch the owner computes itself, so that the busiest of four resources finishes first.

The loads of the caller's and the owner's CPU and network are straight lines in ``d``, the number computed at the owner. Their
maximum is convex, so its least value lies at an end or next to where two lines cross.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from adaptivejoin.functions.costs import CostProfile

LINES = ("lane_cpu", "lane_net", "home_cpu", "home_net")


def batch_lines(ships: DataFrame, profile: CostProfile) -> DataFrame:
    """One row a batch (lane, home, batch_no) with b calls and, of each line, intercept ``*_0`` and slope ``*_1`` in bytes' time.

    Batches of one number are decided at the same time; those of smaller numbers are charged with half of their calls returned: no
    recursion, so each side needs one running sum. ``ships``
    has lane, home, batch_no, value_bytes, ``local_before``, the calls that the lane computes itself up to there, and
    ``asked_before``, the bytes of its requests for values and of their replies (see ``with_lane_work``).
    """
    p, req = profile, profile.key_bytes + profile.param_bytes
    b = ships.groupBy("lane", "home", "batch_no").agg(F.count("*").alias("b"), F.sum("value_bytes").alias("bytes"), F.max("local_before").alias("local"), F.max("asked_before").alias("asked"))
    b = b.withColumn("val", F.floor(F.col("bytes") / F.col("b")).cast("long")).withColumn("half", F.floor(F.col("b") / 2).cast("long"))
    sent_back = F.col("half") * F.col("val") + (F.col("b") - F.col("half")) * p.result_bytes
    of_lane = W.partitionBy("lane").orderBy("batch_no").rangeBetween(W.unboundedPreceding, -1)
    of_home = W.partitionBy("home").orderBy("batch_no").rangeBetween(W.unboundedPreceding, -1)
    before = lambda x, w: F.coalesce(F.sum(x).over(w), F.lit(0))
    b = b.withColumns({
        "back": sent_back,
        "lane_returned": before(F.col("half"), of_lane), "lane_calls": before(F.col("b"), of_lane), "lane_bytes": before(sent_back, of_lane),
        "home_kept": before(F.col("b") - F.col("half"), of_home), "home_bytes": before(sent_back, of_home),
    })
    n, v = F.col("b"), F.col("val")
    return b.select(
        "lane", "home", "batch_no", "b", "val",
        (p.lane_cpu_us * p.bandwidth * (F.col("local") + F.col("lane_returned") + n)).alias("lane_cpu_0"), F.lit(-p.lane_cpu_us * p.bandwidth).cast("long").alias("lane_cpu_1"),
        (req * (F.col("lane_calls") + n) + F.col("asked") + F.col("lane_bytes") + n * v).alias("lane_net_0"), (p.result_bytes - v).alias("lane_net_1"),
        (p.home_cpu_us * p.bandwidth * F.col("home_kept")).alias("home_cpu_0"), F.lit(p.home_cpu_us * p.bandwidth).cast("long").alias("home_cpu_1"),
        (F.col("home_bytes") + n * v).alias("home_net_0"), (p.result_bytes - v).alias("home_net_1"),
    )


def with_lane_work(routed: DataFrame, seq: tuple[str, ...], profile: CostProfile) -> DataFrame:
    """``routed`` with what its lane has to do besides shipping, up to each row: calls on values that it holds, and bytes of the
    requests for values and their replies. One running sum a lane."""
    w = W.partitionBy("lane").orderBy(*seq).rowsBetween(W.unboundedPreceding, 0)
    own, fetch = F.col("route") != "ship", F.col("route") == "fetch"
    asked = F.when(fetch, profile.key_bytes + F.col("value_bytes")).otherwise(0)
    return routed.withColumns({"local_before": F.sum(own.cast("long")).over(w), "asked_before": F.sum(asked.cast("long")).over(w)})


def split_sequential(batches: list[dict], profile: CostProfile, alpha_num: int = 1, alpha_den: int = 2) -> list[int]:
    """d of each batch when its predecessors are charged with what was decided for them: the owner knows its own past exactly, and
    what other owners return to a lane from the lane's smoothed history, one batch old. ``batches`` (lane, home, b, val, local,
    asked) come in the order in which they are decided; state is a few numbers a lane and owner."""
    p, out = profile, []
    kept: dict = {}  # home: calls, bytes sent back
    back: dict = {}  # (lane, home): calls and bytes that earlier batches returned
    history: dict = {}  # lane: smoothed share of calls returned, in 1/1024, and calls shipped to each home
    shipped: dict = {}
    for x in batches:
        lane, home, b, val = x["lane"], x["home"], x["b"], x["val"]
        share = history.get(lane, 512)
        others = sum(n for h, n in shipped.get(lane, {}).items() if h != home)
        ret_other = others * share // 1024
        own_back, own_bytes = back.get((lane, home), (0, 0))
        home_calls, home_bytes = kept.get(home, (0, 0))
        other_bytes = ret_other * val + (others - ret_other) * p.result_bytes
        out_bytes = (p.key_bytes + p.param_bytes) * (sum(shipped.get(lane, {}).values()) + b)

        def time(d: int) -> int:
            reply = d * p.result_bytes + (b - d) * val  # noqa: B023
            return max(
                p.lane_cpu_us * p.bandwidth * (x["local"] + ret_other + own_back + b - d),  # noqa: B023
                out_bytes + x["asked"] + other_bytes + own_bytes + reply,  # noqa: B023
                p.home_cpu_us * p.bandwidth * (home_calls + d),  # noqa: B023
                home_bytes + reply,  # noqa: B023
            )

        d = min(range(b + 1), key=lambda d: (time(d), d))
        out.append(d)
        reply = d * p.result_bytes + (b - d) * val
        kept[home] = home_calls + d, home_bytes + reply
        back[lane, home] = own_back + b - d, own_bytes + reply
        history[lane] = (alpha_num * ((b - d) * 1024 // b) + (alpha_den - alpha_num) * share) // alpha_den
        shipped.setdefault(lane, {})[home] = shipped.get(lane, {}).get(home, 0) + b
    return out


def time_at(d: Column) -> Column:
    return F.greatest(*[F.col(f"{x}_0") + F.col(f"{x}_1") * d for x in LINES])


def split_exact(lines: DataFrame) -> DataFrame:
    """``d`` and ``time``: the least ``d`` of the cheapest, from the ends and both sides of every crossing. No user code."""
    tries = [F.lit(0).cast("long"), F.col("b").cast("long")]
    for i, x in enumerate(LINES):
        for y in LINES[i + 1 :]:
            gap = F.col(f"{x}_1") - F.col(f"{y}_1")
            at = F.when(gap != 0, F.floor((F.col(f"{y}_0") - F.col(f"{x}_0")) / gap).cast("long")).otherwise(0)
            tries += [F.greatest(F.lit(0), F.least(F.col("b"), at)), F.greatest(F.lit(0), F.least(F.col("b"), at + 1))]
    best = F.array_min(F.transform(F.array(*tries), lambda d: F.struct(time_at(d).alias("time"), d.alias("d"))))
    return lines.withColumn("best", best).withColumns({"d": F.col("best.d"), "time": F.col("best.time")}).drop("best")


def descend(a: np.ndarray, s: np.ndarray, b: np.ndarray, rounds: int = 40) -> np.ndarray:
    """d by descent along the slope of the busiest line with halving steps, then a look at both neighbours; rows at once."""
    d = b / 2.0
    step = np.maximum(b / 2.0, 1.0)
    rows = np.arange(len(b))
    for _ in range(rounds):
        busiest = (a + s * d[:, None]).argmax(1)
        d = np.clip(d - np.sign(s[rows, busiest]) * step, 0, b)
        step = step / 2
    near = np.clip(np.floor(d)[:, None] + np.arange(-1, 3)[None], 0, b[:, None])
    cost = (a[:, None] + s[:, None] * near[:, :, None]).max(2)
    return near[rows, cost.argmin(1)].astype(np.int64)


def split_descent(lines: DataFrame) -> DataFrame:
    """The same by descent, vectorised over batches."""
    cols = [f"{x}_{i}" for x in LINES for i in (0, 1)]

    @F.pandas_udf("long")
    def at(b: pd.Series, *c: pd.Series) -> pd.Series:
        m = np.stack([x.to_numpy(float) for x in c], 1)
        return pd.Series(descend(m[:, ::2], m[:, 1::2], b.to_numpy(float)))

    return lines.withColumn("d", at("b", *cols)).withColumn("time", time_at(F.col("d")))
