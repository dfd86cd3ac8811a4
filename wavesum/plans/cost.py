"""Costs: messages between sites and coordinator, shuffled bytes, wall time, and a bandwidth model."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed: bytes of a key, a count at a site, a coefficient or sketch cell, a site id; a null marker takes none.
KEY, COUNT, VALUE, SITE = 4, 4, 8, 4
WIDTHS = {"counts": KEY + COUNT, "coefs": KEY + VALUE, "marked": KEY + SITE + VALUE, "keys": KEY, "cells": KEY + VALUE}
#: Fixed: the link of the published cluster, 100 Mb/s.
LINK_BITS = 100_000_000


@dataclass
class Ledger:
    """Pairs and bytes by phase, upward and downward."""

    entries: list[dict] = field(default_factory=list)

    def record(self, phase: str, df: DataFrame, kind: str) -> Ledger:
        """Counts the messages df under a width; with kind `two_stage`, rows without a count are bare keys."""
        if kind == "two_stage":
            pairs, bare = df.agg(F.count("*"), F.sum(F.col("cnt").isNull().cast("long"))).first()
            size = pairs * KEY + (pairs - (bare or 0)) * COUNT
        else:
            pairs = df.count()
            size = pairs * WIDTHS[kind]
        self.entries.append({"phase": phase, "pairs": pairs, "bytes": size})
        return self

    def broadcast(self, phase: str, size: int) -> Ledger:
        """Downward bytes: a threshold is 8 a site, a candidate id 4 a site."""
        self.entries.append({"phase": phase, "pairs": 0, "bytes": size})
        return self

    def rounds(self, phases: list[dict]) -> Ledger:
        """The phases of a top-k result."""
        for p in phases:
            self.entries.append({"phase": f"phase {p['phase']}", "pairs": p["pairs"], "bytes": p["pairs"] * WIDTHS["marked"]})
            if p.get("down_bytes"):
                self.broadcast(f"phase {p['phase']} down", p["down_bytes"])
        return self

    @property
    def pairs(self) -> int:
        return sum(e["pairs"] for e in self.entries)

    @property
    def bytes(self) -> int:
        return sum(e["bytes"] for e in self.entries)


def timed(run: Callable[[], object]) -> tuple[object, float]:
    """A result and the wall seconds of making it, actions and rounds included."""
    began = time.perf_counter()
    out = run()
    return out, time.perf_counter() - began


def force(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def physical(spark: SparkSession, run: Callable[[], object]) -> dict:
    """Bytes that the stages of a run wrote to shuffles, from the status store."""
    store = spark.sparkContext._jsc.sc().statusStore()
    seen = lambda: {(s.stageId(), s.attemptId()): s for s in _seq(store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None))}
    before = set(seen())
    run()
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    new = [s for k, s in seen().items() if k not in before]
    return {"stages": len(new), "shuffle_write": sum(s.shuffleWriteBytes() for s in new), "shuffle_records": sum(s.shuffleWriteRecords() for s in new), "input": sum(s.inputBytes() for s in new)}


def _seq(scala) -> list:
    return [scala.apply(i) for i in range(scala.size())]


def model(compute_s: float, size: float, share: float) -> float:
    """Seconds of a run that computes for compute_s and moves `size` bytes over a share of the link."""
    return compute_s + size * 8 / (LINK_BITS * share)


def worked_sizes(m: int, eps: float, key: int = KEY) -> dict[str, float]:
    """Bytes that the samplers send at most for given m and eps: all sampled keys, the floor's and the two-stage bound.

    A two-stage run sends sqrt(m) / eps certain pairs and as many bare keys in expectation.
    """
    root = m**0.5 / eps
    return {"uniform": key / eps**2, "floor": key * m / eps, "two_stage": key * root * 2, "two_stage_pairs": 2 * root}
