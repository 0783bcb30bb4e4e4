"""Cost measures: grammar sizes, ranks, depth, the byte model of each component, and timers."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

import numpy as np

from treegrammar.grammar.model import Grammar

STATS_SCHEMA = "edges long, n_rules long, start_nodes long, rank long, depth long, rank0 long, rank1 long, rank2 long, rank3up long, nodes long, elements long, rules_bytes double, tag_bytes double, bp_bytes double, ex_bytes double, jump_bytes double, map_bytes double, skip_bytes double, count_bytes double, serialize_bytes double, nodes_per_bit double"


def model_bytes(n_rules: int, start: int, labels: int, map_ints: int = 0) -> dict[str, float]:
    """Modelled bytes: a rule is one 64-bit word; start tags take a symbol each; the shape 2.5 bits a node or an explicit
    table; the jump table a bit for every rule and label; maps and skip tables 32-bit integers."""
    log = lambda x: math.ceil(math.log2(x)) if x > 1 else 1
    return {
        "rules_bytes": 8.0 * n_rules, "tag_bytes": start * log(n_rules + labels) / 8, "bp_bytes": 2.5 * start / 8, "ex_bytes": start * log(start) / 8,
        "jump_bytes": n_rules * labels / 8, "map_bytes": 4.0 * map_ints, "skip_bytes": 4.0 * start,
    }


def totals(m: dict[str, float]) -> dict[str, float]:
    """The index for counting, and with one map and one skip table for materializing or serializing."""
    count = m["rules_bytes"] + m["tag_bytes"] + m["ex_bytes"] + m["jump_bytes"]
    return {"count_bytes": count, "serialize_bytes": count + m["map_bytes"] + m["skip_bytes"]}


def shard_stats(g: Grammar) -> dict[str, int | float]:
    rank = g.rank[g.first_rule :]
    hist = np.bincount(np.minimum(rank, 3), minlength=4)
    nodes = int(g.totals("node").sum())
    m = model_bytes(g.n_rules, len(g.start), g.n_labels, int((rank + 1).sum()))
    m |= totals(m)
    return {
        "edges": g.edges(), "n_rules": g.n_rules, "start_nodes": len(g.start), "rank": int(rank.max(initial=0)), "depth": g.depth(), "rank0": int(hist[0]), "rank1": int(hist[1]), "rank2": int(hist[2]),
        "rank3up": int(hist[3]), "nodes": nodes, "elements": int(g.totals("elem").sum()), **m, "nodes_per_bit": nodes / max(1.0, 8 * m["count_bytes"]),
    }


def best_of(run: Callable[[], object], times: int = 3) -> float:
    """The best wall time of a few runs, in seconds."""
    out = []
    for _ in range(times):
        t = time.perf_counter()
        run()
        out.append(time.perf_counter() - t)
    return min(out)
