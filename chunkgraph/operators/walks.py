"""Local clustering in batches of seeds: a task holds the walks of a batch as arrays and asks for the neighbour lists it lacks.

A round hands each batch the lists of all vertices that had mass above the threshold, and every walk goes on until it needs
another list. So lists are shuffled, a few rounds of them, and no walk's states step by step.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import settle

#: Edges that the walks of a batch push in a step, at most: those of a walk are under 1/eps. And seeds of a batch, at most.
BATCH_EDGES, BATCH_SEEDS = 1 << 21, 512
#: A row is a seed: its batch, the steps done, its state (vertex, mass, degree), the vertices whose lists it has or lacks, and
#: those whose lists the batch asks for next (each by one of the round's seeds): such vertices, or a last state's.
_STATE = "seed long, batch long, step int, vids array<long>, ps array<double>, degs array<long>, known array<long>, asked array<long>"
_MEMBERS = "seed long, vid long, conductance double"
#: Scores and conductances are compared at 12 decimals, halves up.
_UNITS = 1e12


def batches_of(seeds: int, eps: float) -> int:
    return -(-seeds // max(1, min(BATCH_SEEDS, int(BATCH_EDGES * max(eps, 0.0)))))


def _lists(column: pa.ChunkedArray) -> tuple[np.ndarray, pa.Array]:
    """Lengths and elements of a column of lists."""
    whole = column.combine_chunks()
    return whole.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64), whole.flatten()


def _numbers(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    lengths, flat = _lists(column)
    return lengths, flat.to_numpy(zero_copy_only=False)


def _packed(lengths: np.ndarray, flat: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(lengths)]), pa.int32()), pa.array(flat))


def _spread(begin: np.ndarray, count: np.ndarray) -> np.ndarray:
    """begin, begin + 1, ... of each range, one after another."""
    return np.repeat(begin - (np.cumsum(count) - count), count) + np.arange(count.sum())


def _advance(state: pa.Table, lists: pa.Table, eps: float, steps: int) -> pa.Table:
    """The batch's walks, as far as its lists (vid, near) go."""
    n, step = state.num_rows, state["step"].to_numpy().astype(np.int64)
    (held, vids), (_, ps), (_, degs), (listed, known) = (_numbers(state[c]) for c in ("vids", "ps", "degs", "known"))
    owners, (count, near) = lists["vid"].to_numpy(), _lists(lists["near"])
    elem, far = (near.field(c).to_numpy(zero_copy_only=False) for c in ("dst", "far"))
    order = np.argsort(owners)
    slot = order[np.searchsorted(owners, known, sorter=order)]
    begin, count = (np.cumsum(count) - count)[slot], count[slot]
    edge = _spread(begin, count)
    # all (seed, vertex) that have mass or can get some from the lists at hand, numbered in order of both
    names, place = np.unique(np.concatenate([known, vids, elem]), return_inverse=True)
    a, b, m = len(known), len(known) + len(vids), len(names)
    of_known, of_vids = np.repeat(np.arange(n), listed), np.repeat(np.arange(n), held)
    keys, at = np.unique(np.concatenate([of_known * m + place[:a], of_vids * m + place[a:b], np.repeat(of_known, count) * m + place[b:][edge]]), return_inverse=True)
    source, target = np.repeat(at[:a], count), at[b:]
    who, deg, has, p = keys // m, np.zeros(len(keys), np.int64), np.zeros(len(keys), bool), np.zeros(len(keys))
    deg[target], deg[at[a:b]], deg[at[:a]] = far[edge], degs, count
    has[at[:a]], p[at[a:b]] = True, ps
    able, threshold, twice = deg > 0, eps * deg, 2 * np.maximum(deg, 1)
    among = lambda flags: np.bincount(who[flags], minlength=n) > 0
    going = step < steps
    while going.any():
        on = able & (p > 0) & (p >= threshold) & going[who]
        going &= ~among(on & ~has)  # these wait for lists
        on &= going[who]
        stuck = going & ~among(on)
        step[stuck] = steps
        going &= ~stuck
        step[going] += 1
        sent = np.where(on, p, 0.0)
        p = np.where(going[who], sent / 2 + np.bincount(target, (sent / twice)[source], len(keys)), p)
        going &= step < steps
    waits = (step < steps)[who]
    asks, kept = waits & (has | able & (p > 0) & (p >= threshold)), p > 0
    vid, sizes = names[keys % m], lambda flags: np.bincount(who[flags], minlength=n)
    full = sizes(kept)
    once = np.zeros(len(keys), bool)
    for flags in (np.flatnonzero(asks), np.flatnonzero(kept & ~waits)):
        once[flags[np.unique(keys[flags] % m, return_index=True)[1]]] = True
    columns = [state["seed"], state["batch"], pa.array(step, pa.int32()), _packed(full, vid[kept]), _packed(full, p[kept]), _packed(full, deg[kept])]
    columns += [_packed(sizes(flags), vid[flags]) for flags in (asks, once)]
    return pa.table(columns, names=state.column_names)


def _cut(state: pa.Table, lists: pa.Table, total: int) -> pa.Table:
    """(seed, vid, conductance): members of each walk's first prefix of least conductance. Lists (vid, to) have each edge
    at its end of smaller degree; all edges of a vertex count as leaving, and an edge inside takes two back at its later end."""
    (held, vids), (_, ps), (_, degs) = (_numbers(state[c]) for c in ("vids", "ps", "degs"))
    seeds, who, real = state["seed"].to_numpy(), np.repeat(np.arange(state.num_rows), held), degs > 0
    who, vids, degs, score = who[real], vids[real], degs[real], np.floor(ps[real] / degs[real] * _UNITS + 0.5)
    if not len(who):
        return pa.table([pa.array([], t) for t in (pa.int64(), pa.int64(), pa.float64())], names=["seed", "vid", "conductance"])
    names, place = np.unique(vids, return_inverse=True)
    keys = who * len(names) + place
    by_key, ranked = np.argsort(keys), np.lexsort((vids, -score, who))
    rank = np.empty(len(who), np.int64)
    rank[ranked] = np.arange(len(who))
    # edges inside: from a (seed, vertex) whose vertex has a list to (seed, element), if that is there
    owners, (count, to) = lists["vid"].to_numpy(), _numbers(lists["to"])
    size, begin = np.zeros(len(names), np.int64), np.zeros(len(names), np.int64)
    spot = np.searchsorted(names, owners)
    size[spot], begin[spot] = count, np.cumsum(count) - count
    length = size[place]
    edge, source = _spread(begin[place], length), np.repeat(np.arange(len(who)), length)
    spot = np.minimum(np.searchsorted(names, to), len(names) - 1)
    there = (names[spot] == to)[edge]
    source, wanted = source[there], who[source[there]] * len(names) + spot[edge[there]]
    found = by_key[np.minimum(np.searchsorted(keys, wanted, sorter=by_key), len(keys) - 1)]
    inside = keys[found] == wanted
    source, found = source[inside], found[inside]
    back = np.bincount(np.maximum(rank[source], rank[found]), minlength=len(who)) * 2 - np.bincount(rank[source[source == found]], minlength=len(who))
    who, deg = who[ranked], degs[ranked]
    starts = np.flatnonzero(np.diff(who, prepend=-1))
    lengths = np.diff(starts, append=len(who))
    upto = lambda x: np.cumsum(x) - np.repeat(np.cumsum(x)[starts] - x[starts], lengths)
    volume = upto(deg)
    least = np.minimum(volume, total - volume)
    conductance = np.floor(np.where(least > 0, upto(deg - back) / np.maximum(least, 1), 1.0) * _UNITS + 0.5)
    best = np.repeat(np.minimum.reduceat(conductance, starts), lengths)
    first = np.minimum.reduceat(np.where(conductance == best, np.arange(len(who)), len(who)), starts)
    member = np.arange(len(who)) <= np.repeat(first, lengths)
    return pa.table([seeds[who[member]], vids[ranked][member], best[member] / _UNITS], names=["seed", "vid", "conductance"])


def _asked(state: DataFrame, lists: DataFrame) -> DataFrame:
    """The lists (vid, ...) that the states ask for, with the batch (of)."""
    return state.select(F.col("batch").alias("of"), F.explode("asked").alias("vid")).join(lists, "vid")


def walked(seeds: DataFrame, degrees: DataFrame, near: DataFrame, batches: int, eps: float, steps: int) -> list[DataFrame]:
    """The walks' last states, written, in frames by the round that ended them. near: (vid, near) of every vertex with
    a degree of 1/eps at most; others never pass mass on. seeds: distinct vid."""
    state = seeds.join(degrees, "vid", "left").withColumn("on", F.coalesce(F.lit(1.0) >= eps * F.col("deg"), F.lit(False)))
    none, own = F.array().cast("array<long>"), F.array("vid")
    batch, step = F.pmod(F.xxhash64("vid", F.lit("batch")), F.lit(batches)), F.when(F.col("on"), 0).otherwise(steps)
    state = state.select(
        F.col("vid").alias("seed"), batch.alias("batch"), step.alias("step"), own.alias("vids"), F.array(F.lit(1.0)).alias("ps"),
        F.array(F.coalesce("deg", F.lit(0).cast("long"))).alias("degs"), F.when(F.col("on"), own).otherwise(none).alias("known"), own.alias("asked"),
    )
    done = [settle(state)]
    while done[-1].where(F.col("step") < steps).take(1):
        open_ = done[-1].where(F.col("step") < steps)
        lists = _asked(open_, near).select("of", "vid", "near")
        go = lambda left, right: _advance(left, right, eps, steps)
        done.append(settle(open_.groupBy("batch").cogroup(lists.groupBy("of")).applyInArrow(go, _STATE)))
    return done


def ended(rounds: list[DataFrame], steps: int) -> DataFrame:
    out = rounds[0].where(F.col("step") >= steps)
    for f in rounds[1:]:
        out = out.unionByName(f.where(F.col("step") >= steps))
    return out


def clusters(rounds: list[DataFrame], downhill: DataFrame, total: int, steps: int) -> DataFrame:
    """(seed, vid, conductance) of the walks that `walked` gave; downhill: (vid, to)."""
    states = ended(rounds, steps).select("batch", "seed", "vids", "ps", "degs", "asked")
    lists = _asked(states, downhill).select("of", "vid", "to")
    return states.drop("asked").groupBy("batch").cogroup(lists.groupBy("of")).applyInArrow(lambda left, right: _cut(left, right, total), _MEMBERS)
