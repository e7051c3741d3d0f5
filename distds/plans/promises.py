"""Concurrency promises: what may run at the same time picks the cheapest correct plan. Also their analytic costs."""

from __future__ import annotations

import enum
import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


class Promise(enum.Flag):
    FIND = enum.auto()
    INSERT = enum.auto()
    PUSH = enum.auto()
    POP = enum.auto()
    LOCAL = enum.auto()


class PromiseViolation(ValueError):
    """The log holds operations that the promise rules out."""


@dataclass(frozen=True)
class Plan:
    """What a promise selects, with best-case counts of atomics, reads, writes, local steps and barriers.

    ``each``: the column that counts once for every item of a vector ('' for none). ``blocking``: the last atomic must wait.
    """

    structure: str
    method: str
    promise: str
    plan: str
    a: int = 0
    r: int = 0
    w: int = 0
    local: int = 0
    barrier: int = 0
    each: str = ""
    blocking: bool = False


#: Best-case costs of each operation. A scattered filter touches K words.
K = 4
PLANS = (
    Plan("table", "insert", "find+insert", "merge by max_by", a=2, w=1, blocking=True),
    Plan("table", "insert", "local", "merge in place", local=1),
    Plan("table", "find", "find+insert", "union and window", a=2, r=1, blocking=True),
    Plan("table", "find", "find", "equi-join", r=1),
    Plan("blocked filter", "insert", "any", "window by block", a=1),
    Plan("blocked filter", "find", "any", "join by block", r=1),
    Plan("scattered filter", "insert", "any", "first seq by bit", a=K),
    Plan("scattered filter", "find", "any", "join by bit", r=K),
    Plan("ring", "push", "push+pop", "clamp scan", a=2, w=1, blocking=True),
    Plan("ring", "push", "push", "prefix scan", a=2, w=1),
    Plan("ring", "push", "local", "append in place", local=1),
    Plan("ring", "pop", "push+pop", "clamp scan", a=2, r=1, blocking=True),
    Plan("ring", "pop", "pop", "prefix scan", a=2, r=1),
    Plan("ring", "pop", "local", "read in place", local=1),
    Plan("ring", "push vector", "push", "fold by host", a=2, w=1, each="w"),
    Plan("ring", "pop vector", "pop", "fold by host", a=2, r=1, each="r"),
    Plan("phase queue", "push", "push", "prefix scan", a=1, w=1),
    Plan("phase queue", "pop", "pop", "prefix scan", a=1, r=1),
    Plan("phase queue", "push vector", "push", "fold by host", a=1, w=1, each="w"),
    Plan("phase queue", "pop vector", "pop", "fold by host", a=1, r=1, each="r"),
    Plan("phase queue", "pop", "local", "read in place", local=1),
    Plan("queue", "resize", "collective", "new slots", local=1, barrier=1),
    Plan("queue", "migrate", "collective", "new host", w=1, barrier=1, each="w"),
    Plan("buffer", "insert", "any", "stage, then one exchange", a=1, w=1, local=1, each="w,local"),
)
NAMES = {Promise.FIND | Promise.INSERT: "find+insert", Promise.FIND: "find", Promise.INSERT: "find+insert", Promise.LOCAL: "local", Promise.PUSH | Promise.POP: "push+pop", Promise.PUSH: "push", Promise.POP: "pop"}


def select(structure: str, method: str, promise: Promise) -> Plan:
    """The plan for a promise; the strongest guarantee is the default of every method."""
    want = NAMES[promise]
    for p in PLANS:
        if (p.structure, p.method) == (structure, method) and p.promise in (want, "any", "collective"):
            return p
    raise KeyError((structure, method, want))


def cost_table(spark: SparkSession, numbered: bool = False) -> DataFrame:
    """A row for each plan, if asked for with its place as ``id``."""
    rows = [(p.structure, p.method, p.promise, p.a, p.r, p.w, p.local, p.barrier, p.each, p.blocking, i) for i, p in enumerate(PLANS)]
    df = spark.createDataFrame(rows, "structure string, method string, promise string, a int, r int, w int, local int, barrier int, each string, blocking boolean, id int")
    return df if numbered else df.drop("id")


def ledger(log: DataFrame) -> DataFrame:
    """``log``: structure, method, promise, n (items of a call). Sums of best-case costs."""
    costs = F.broadcast(cost_table(log.sparkSession))
    rows = log.join(costs, ["structure", "method", "promise"])

    def total(c: str):
        return F.sum(F.col(c) * F.when(F.array_contains(F.split("each", ","), c), F.col("n")).otherwise(1)).cast("long").alias(c)

    return rows.groupBy("structure", "method", "promise").agg(F.count("*").cast("long").alias("calls"), *[total(c) for c in ("a", "r", "w", "local", "barrier")])


def measured(df: DataFrame) -> dict[str, int]:
    """What the planned query will cost in Spark's terms: exchanges, sorts, broadcasts, Python nodes."""
    planned = df._jdf.queryExecution().executedPlan().toString()

    def count(pattern: str) -> int:
        return len(re.findall(pattern, planned))

    return {"exchanges": count(r"\bExchange "), "broadcasts": count(r"BroadcastExchange"), "sorts": count(r"\bSort \["), "windows": count(r"\bWindow "), "python": count(r"InArrow|InPandas|EvalPython"), "joins": count(r"Join ")}


def check_promise(log: DataFrame, promise: Promise) -> DataFrame:
    """``log``: phase, op. phase, violations: operations of each phase that the promise rules out."""
    allowed = [p.name.lower() for p in Promise if p in promise]
    return log.groupBy("phase").agg(F.sum(F.when(F.col("op").isin(allowed), 0).otherwise(1)).cast("long").alias("violations"))


def infer_promise(log: DataFrame) -> DataFrame:
    """phase, promise: the weakest promise that each phase keeps, which is the cheapest valid one."""
    ops = log.groupBy("phase").agg(F.array_join(F.array_sort(F.collect_set("op")), "+").alias("ops"))  # a few names
    return ops.select("phase", F.when(F.col("ops") == "insert", "find+insert").otherwise(F.when(F.col("ops") == "pop+push", "push+pop").otherwise(F.col("ops"))).alias("promise"))
