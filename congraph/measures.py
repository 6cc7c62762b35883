"""Cost measures: run times with and without index building, speed-ups and their summary."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Sequence
from statistics import median

from pyspark.sql import DataFrame, SparkSession

from congraph import rules_algebra, rules_binding, suites
from congraph.graph import CongruenceGraph
from congraph.operators.atoms import atom_frames
from congraph.operators.extension import PrefixIndex
from congraph.operators.match import compiled, match


def timed(make: Callable[[], DataFrame], repeats: int = 10) -> float:
    """Least milliseconds of several runs into the noop sink."""
    best = math.inf
    for _ in range(repeats):
        t = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        best = min(best, 1000 * (time.perf_counter() - t))
    return best


def measure_pattern(graph: CongruenceGraph, pattern, repeats: int = 10) -> dict[str, float]:
    """topdown_ms, join_ms (index built on the way), reuse_ms (index tables of an earlier run), index_ms, n_matches."""
    topdown = timed(lambda: match(graph, pattern, strategy="topdown"), repeats)
    join = timed(lambda: match(graph, pattern, strategy="extension"), repeats)
    cq = compiled(pattern)
    frames = atom_frames(graph, cq)
    t = time.perf_counter()
    index = PrefixIndex(frames, cq.keyed, written=True)
    n = match(graph, cq, strategy="extension", frames=frames, index=index).count()
    first = 1000 * (time.perf_counter() - t)
    reuse = timed(lambda: match(graph, cq, strategy="extension", frames=frames, index=index), repeats)
    return {"topdown_ms": topdown, "join_ms": join, "reuse_ms": reuse, "index_ms": max(0.0, first - reuse), "n_matches": n}


def summary(topdown: Sequence[float], join: Sequence[float]) -> dict[str, float]:
    """Wins of each side, the cumulative speed-up, and means and extremes of the speed-ups of the patterns."""
    ratios = [a / b for a, b in zip(topdown, join)]
    n = len(ratios)
    return {
        "wins_join": sum(r > 1 for r in ratios),
        "wins_topdown": sum(r <= 1 for r in ratios),
        "total": sum(topdown) / sum(join),
        "hmean": n / sum(1 / r for r in ratios),
        "gmean": math.exp(sum(map(math.log, ratios)) / n),
        "best": max(ratios),
        "median": median(ratios),
        "worst": min(ratios),
    }


def suite_table(spark: SparkSession, sf_dir: str, name: str, limits: Sequence[int] = (2000,), patterns: Sequence[str] | None = None, repeats: int = 3) -> list[dict]:
    """Rows of suite, graph_nodes, indexed and the summary, two for each size."""

    every = rules_algebra.PATTERNS if name == "algebra" else rules_binding.PATTERNS
    out = []
    for limit in limits:
        done = suites.suite(spark, sf_dir, name, limit, 4, max(4, limit // 100))
        g = CongruenceGraph(spark, relations={s: d.cache() for s, d in done.graph.relations().items()})
        rows = [measure_pattern(g, every[k], repeats) for k in (patterns or every)]
        for indexed, column in ((True, "join_ms"), (False, "reuse_ms")):
            out.append({"suite": name, "graph_nodes": done.nodes[-1], "indexed": indexed, "match_share": round(done.match_share, 3)} | summary([r["topdown_ms"] for r in rows], [r[column] for r in rows]))
    return out
