"""Cost rules: which reduce topology, join, state store, model layout and model family a plan should use."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def predict_reduce_cost(tasks: int, machines: int, size: float, bandwidth: float, fan_in: int = 4, blocks: int | None = None) -> dict[str, float]:
    """Seconds of network on the critical path of each topology: bytes into its busiest receivers over the bandwidth. Early partials cost no network."""
    blocks = blocks or machines
    unit = size / bandwidth
    return {
        "flat": tasks * unit,
        "sqrt": 2 * math.ceil(math.sqrt(tasks)) * unit,
        "local_sqrt": 2 * math.ceil(math.sqrt(machines)) * unit,
        "tree": fan_in * math.ceil(round(math.log(max(machines, 2), fan_in), 9)) * unit,
        "blocks": tasks * unit / blocks + unit,
    }


def reduce_cost_columns(machines: Column, tasks: Column, size: float, bandwidth: float, fan_in: int = 4) -> dict[str, Column]:
    """The same for a column of machine numbers, without blocks."""
    unit = F.lit(size) / F.lit(bandwidth)
    depth = F.ceil(F.round(F.log(F.greatest(machines, F.lit(2))) / F.lit(math.log(fan_in)), 9))
    return {"flat": tasks * unit, "sqrt": 2 * F.ceil(F.sqrt(tasks)) * unit, "local_sqrt": 2 * F.ceil(F.sqrt(machines)) * unit, "tree": fan_in * depth * unit}


def choose_reduce(tasks: int, machines: int, size: float, bandwidth: float, latency: float = 0.2, block_from: float = 1e6) -> str:
    """Layers add their latency; vectors above `block_from` bytes may be cut in blocks."""
    seconds = predict_reduce_cost(tasks, machines, size, bandwidth)
    layers = {"flat": 1, "sqrt": 2, "local_sqrt": 3, "tree": 1 + math.ceil(math.log(max(machines, 2), 4)), "blocks": 2}
    options = {k: s + layers[k] * latency for k, s in seconds.items() if k != "blocks" or size >= block_from}
    return min(options, key=lambda k: (options[k], layers[k]))


def choose_join(left_bytes: float, right_bytes: float, sorted_left: bool, broadcast_limit: float = 64e6) -> str:
    """broadcast a side of a known small size; merge where the larger side is laid out by the key; else hash unless the smaller side is too large to build."""
    small = min(left_bytes, right_bytes)
    if small <= broadcast_limit:
        return "broadcast"
    return "merge" if sorted_left or small > 50 * broadcast_limit else "shuffle_hash"


def choose_store(vertices: int, expected_active: float) -> str:
    """delta_merge where few vertices change in a round, else replace; the log is never cheaper."""
    return "delta_merge" if expected_active < 0.1 * vertices else "replace"


def choose_layout(dimension: int, limit_bytes: float = 512e6, entry_bytes: float = 8) -> str:
    """Weights as literals up to a few hundred, broadcast up to a limit, a table beyond. entry_bytes: of one weight and its key."""
    if dimension <= 512:
        return "literal"
    return "broadcast_dense" if entry_bytes * dimension <= limit_bytes else "feature_table"


def choose_model_family(model_bytes: float, data_bytes: float) -> str:
    """Models as large as the data are local (vertices); small ones are global."""
    return "vertex" if model_bytes > 0.05 * data_bytes else "mru"


def choose_early_grouping(messages: float, distinct_per_task: float, tasks: int) -> bool:
    """Combining at the sender pays if it removes a tenth of the messages."""
    return distinct_per_task * tasks <= 0.9 * messages
