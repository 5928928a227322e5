"""Count-min sketches whose cells are approximate counters: relations (group..., i, col, state)."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tallymill.functions.counters import advance, counter_read, merge_exact, merge_exact_col, merge_round, merge_round_col, stays, thresholds
from tallymill.functions.hashing import hash_np
from tallymill.functions.keyed import mixed, uniform, uniforms_text
from tallymill.operators import cms
from tallymill.params import SketchParams


def draws(df: DataFrame, key: str, p: SketchParams, group: Sequence[str], event: Sequence[str]) -> DataFrame:
    """(group..., i, col, event..., u): one row for each cell an increment touches. Independent
    counters draw for every hash row, correlated ones share the event's draw."""
    ids = [F.col(e) for e in event]
    spread = df.select(*group, *event, F.explode(cms.addresses(key, p, cms._scoped(p, group))).alias("at")).select(*group, *event, "at.i", "at.col")
    u = uniform("ci", p.seed, *ids, F.col("i")) if p.counter == "independent" else uniform("cc", p.seed, *ids)
    return spread.withColumn("u", u)


def fold_cells(rows: DataFrame, group: Sequence[str], order: Sequence[str], base: float, cap: int = 255) -> DataFrame:
    """State of every group of rows(group..., order..., u) after its draws in order, streamed."""
    table = thresholds(base, cap)
    schema = T.StructType([rows.schema[g] for g in group] + [T.StructField("state", T.IntegerType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, s, kinds = None, 0, []
        for b in batches:
            kinds, done = [b.column(g).type for g in group], []
            for key, u in zip(zip(*[b.column(g).to_pylist() for g in group]), b.column("u").to_pylist()):
                if key != now:
                    if now is not None:
                        done.append((*now, s))
                    now, s = key, 0
                if u < table[s] and s < cap:
                    s += 1
            yield pa.record_batch([pa.array(c, k) for c, k in zip(zip(*done) if done else [()] * (len(group) + 1), [*kinds, pa.int32()])], names=schema.names)
        if now is not None:
            yield pa.record_batch([pa.array([v], k) for v, k in zip((*now, s), [*kinds, pa.int32()])], names=schema.names)

    return cms.ordered(rows.select(*group, *[o for o in order if o not in group], "u"), group, order).mapInArrow(run, schema)


#: States that a task holds while it leaves out increments; beyond, it goes on from none.
HELD = 1 << 24


def _raised(flat: np.ndarray, at: np.ndarray, levels: np.ndarray) -> list[int]:
    """Conservative steps in place, in order: at[i, row] are the cells of increments, levels the least states that
    their draws do not move. Tells the rows that moved a state; a cell only rises, so others are found at once."""
    rows, now, kept = np.flatnonzero(flat[at].min(0) < levels), {}, []
    for r, cells, before, level in zip(rows.tolist(), at[:, rows].T.tolist(), flat[at[:, rows]].T.tolist(), levels[rows].tolist()):
        states = [now.get(c, s) for c, s in zip(cells, before)]
        least = min(states)
        if least < level:
            now |= {c: least + 1 for c, s in zip(cells, states) if s == least}
            kept.append(r)
    _set(flat, now)
    return kept


def _stepped(flat: np.ndarray, at: np.ndarray, levels: np.ndarray) -> list[int]:
    """The same for one cell an increment, at[row]."""
    before = flat[at]
    rows, now, kept = np.flatnonzero(before < levels), {}, []
    for r, cell, state, level in zip(rows.tolist(), at[rows].tolist(), before[rows].tolist(), levels[rows].tolist()):
        state = now.get(cell, state)
        if state < level:
            now[cell] = state + 1
            kept.append(r)
    _set(flat, now)
    return kept


def _set(flat: np.ndarray, now: dict[int, int]) -> None:
    flat[np.fromiter(now, np.int64, len(now))] = np.fromiter(now.values(), np.int64, len(now))


def _levels(u: np.ndarray, p: SketchParams) -> np.ndarray:
    """The least states that draws do not move."""
    return np.minimum(np.searchsorted(-np.array(thresholds(p.base, p.cap)), -u, "left"), p.cap)


def moving(df: DataFrame, key: str, kinds: Sequence[SketchParams], group: Sequence[str], event: Sequence[str]) -> DataFrame:
    """(group..., event..., key) of df without increments that move no state of any of several sketches; build() gives
    the same for what is left.

    A step only raises states, and a draw that did not move a lower state does not move a higher one. So the states
    that some of the increments lead to are lower bounds of those that all lead to, and an increment that moves
    nothing among those of its partition before it moves nothing in the whole fold. At most as many are left of a
    partition as it passes states, however many it has."""
    names = list(dict.fromkeys([*group, *event, key]))
    ids = F.concat_ws("|", *[F.col(e).cast("string") for e in event])
    scoped = [bool(cms._scoped(p, group)) and p.rule == "plain" for p in kinds]
    # of plain sketches that differ in l the longest has the others' hash rows
    same = [replace(p, l=1) if p.rule == "plain" else p for p in kinds]
    kinds = [(p, c) for p, c, k in zip(kinds, scoped, same) if p.l == max(q.l for q, o in zip(kinds, same) if o == k)]
    kinds = list(dict.fromkeys(kinds))
    seeds = sorted({p.seed for p, _ in kinds})
    rows = df.select(*names).sortWithinPartitions(*dict.fromkeys([*event, key]))
    rows = rows.select(*names, F.col(key).cast("long").alias("_own"), ids.alias("_id"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slots, flats = {}, [np.zeros(0, np.int32)] * len(kinds)
        for b in batches:
            if not b.num_rows:
                continue
            code, keys = np.zeros(b.num_rows, np.int64), b.column("_own")
            for g in group:
                own = b.column(g).dictionary_encode("encode")
                code = np.unique(code * len(own.dictionary) + own.indices.to_numpy(zero_copy_only=False), return_inverse=True)[1]
            told = [tuple(b.column(g)[r].as_py() for g in group) for r in np.unique(code, return_index=True)[1].tolist()]
            slot = np.array([slots.setdefault(name, len(slots)) for name in told], np.int64)[code]
            null, keys, own = keys.is_null().to_numpy(zero_copy_only=False), keys.fill_null(0).to_numpy(zero_copy_only=False), {}

            def once(name: tuple, make) -> np.ndarray:
                if name not in own:
                    own[name] = make()
                return own[name]

            def columns(p: SketchParams, i: int, by: bool) -> np.ndarray:
                if not by:
                    return np.where(null, p.w, hash_np(keys, i, p))
                part = b.column(group[0])
                return np.where(null | part.is_null().to_numpy(zero_copy_only=False), p.w, hash_np(keys, i, p, part.cast(pa.int64()).fill_null(0).to_numpy(zero_copy_only=False)))

            draw = {s: uniforms_text(f"cc|{s}|", b.column("_id"), [""])[0] for s in seeds if any(p.seed == s and (p.counter, p.rule) != ("independent", "plain") for p, _ in kinds)}
            each = {s: uniforms_text(f"ci|{s}|", b.column("_id"), [f"|{i}" for i in range(most)]) for s in seeds if (most := max((p.l for p, _ in kinds if p.seed == s and (p.counter, p.rule) == ("independent", "plain")), default=0))}
            kept = np.zeros(b.num_rows, bool)
            for n, (p, by) in enumerate(kinds):
                size = p.l * (p.w + 1)  # a last column is that of null keys
                if len(slots) * size > len(flats[n]):
                    flats[n] = np.concatenate([flats[n], np.zeros(max(len(slots) * size, 2 * len(flats[n])) - len(flats[n]), np.int32)])
                at = [slot * size + i * (p.w + 1) + once(("col", p.seed, p.w, i, by), lambda: columns(p, i, by)) for i in range(p.l)]
                single = (p.counter, p.rule) == ("independent", "plain")
                level = [once(("level", p.seed, p.base, p.cap, i if single else "all"), lambda: _levels(each[p.seed][i] if single else draw[p.seed], p)) for i in range(p.l)]
                if p.rule == "plain":
                    for x, y in zip(at, level):
                        kept[_stepped(flats[n], x, y)] = True
                else:
                    kept[_raised(flats[n], np.stack(at), level[0])] = True
            if sum(len(f) for f in flats) > HELD:
                slots, flats = {}, [np.zeros(0, np.int32)] * len(kinds)
            yield b.select(names).filter(pa.array(kept))

    return rows.mapInArrow(run, df.select(*names).schema)


def build(df: DataFrame, key: str, p: SketchParams, group: Sequence[str], event: Sequence[str]) -> DataFrame:
    """(group..., i, col, state) of the increments of df in the order of event, which must tell
    increments of a group apart. Plain rules fold each cell on its own, in parallel; the
    conservative rule folds each group. Increments that move no state in their partition are not shuffled."""
    df = moving(df, key, [p], group, event)
    if p.rule == "plain":
        return fold_cells(draws(df, key, p, group, event), [*group, "i", "col"], event, p.base, p.cap)

    def step(m: np.ndarray, keys: np.ndarray, u: np.ndarray) -> None:
        at = np.stack([i * p.w + hash_np(keys, i, p) for i in range(p.l)])
        _raised(m.reshape(-1), at, _levels(u, p))

    keyed = df.withColumn("u", uniform("cc", p.seed, *[F.col(e) for e in event]))
    cells = cms.folded(keyed, group, list(dict.fromkeys([*event, key])), [key, "u"], (p.l, p.w), step, "state")
    return cells.withColumn("state", F.col("state").cast("int"))


#: Shards of a component whose keys are counted on their own before they are merged.
SHARDS = 32


def build_bulk(df: DataFrame, key: str, p: SketchParams, group: Sequence[str] = (), weight: str | None = None, shards: int = SHARDS) -> DataFrame:
    """(group..., i, col, state or cell): the sketch of the increments of df from counts, not one by one.

    Increments are summed before any shuffle, so a task sends at most one row for each cell
    (plain exact cells and independent counters) or each distinct key, and a key that holds a third
    of all increments is one row. Independent counters jump to the state of a cell's count; the law
    is that of single increments. Correlated counters and the conservative rule take keys one after
    another, in shards of a component: exact cells of shards add, states are merged with a draw that
    a component's cells share. The order of increments is by key, not that of build()."""
    if p.rule == "plain" and p.counter in ("exact", "independent"):
        cells = cms.cm_build(df, key, p, group, weight)
        return cells if p.counter == "exact" else _jumped(cells, p, group)
    n = F.sum(F.col(weight)).alias("n") if weight else F.count("*").alias("n")
    counts = df.groupBy(*group, key).agg(n).select(*group, F.col(key).cast("long").alias("own"), F.col("n").cast("long").alias("n"), F.pmod(F.xxhash64(key), F.lit(shards)).cast("int").alias("shard"))
    by, value = [*group, "shard"], "cell" if p.counter == "exact" else "state"

    def step(m: np.ndarray, keys: np.ndarray, n: np.ndarray) -> None:
        at = np.stack([i * p.w + hash_np(keys, i, p) for i in range(p.l)])
        flat = m.reshape(-1)
        if p.counter == "correlated":
            advance_keys(flat, at, n, p, p.seed, keys)
        else:
            for cells, more in zip(at.T, n.tolist()):
                flat[cells] = np.maximum(flat[cells], flat[cells].min() + more)

    parts = cms.folded(counts, by, ["own"], ["own", "n"], (p.l, p.w), step, value)
    if p.counter == "exact":
        return parts.groupBy(*group, "i", "col").agg(F.sum("cell").alias("cell"))
    # at most `shards` states of a cell meet, in the order of their shards
    states = F.array_sort(F.collect_list(F.struct("shard", "state")))
    cap = min(p.cap, 1023)

    def meet(state, other):
        return merge_round_col(state.cast("int"), other["state"].cast("int"), uniform("mg", p.seed, *[F.col(g) for g in group], other["shard"]), p.base, cap)

    met = parts.groupBy(*group, "i", "col").agg(states.alias("states"))
    return met.select(*group, "i", "col", F.aggregate("states", F.lit(0), lambda s, x: meet(s, x).cast("int")).alias("state"))


def _jumped(cells: DataFrame, p: SketchParams, group: Sequence[str]) -> DataFrame:
    """States of counters that were stepped as often as exact cells say."""
    rows = cells.select(*group, "i", "col", F.col("cell").cast("long").alias("cell"), F.xxhash64(*group, "i", "col").alias("id"))
    schema = T.StructType([*(rows.schema[c] for c in (*group, "i", "col")), T.StructField("state", T.IntegerType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n = b.column("cell").to_numpy()
            state = advance(np.zeros(len(n), np.int64), n, p.base, p.cap, p.seed, b.column("id").to_numpy())
            yield pa.record_batch([*(b.column(c) for c in schema.names[:-1]), pa.array(state.astype(np.int32))], names=schema.names)

    return rows.mapInArrow(run, schema)


def query(cells: DataFrame, keys: DataFrame, key: str, p: SketchParams, group: Sequence[str] = ()) -> DataFrame:
    """(group..., key, state, est): the read of the least state; absent cells are at state 0."""
    at = cms.looked_up(cells, keys, key, p, group, "state")
    least = at.groupBy(*group, key).agg(F.min("state").cast("int").alias("state"))
    table = min(p.cap, 1023)
    beyond = (F.pow(F.lit(p.base), F.col("state")) - 1) / (p.base - 1)
    return least.withColumn("est", F.when(F.col("state") <= table, counter_read(F.col("state"), p.base, table)).otherwise(beyond))


def merge(a: DataFrame, b: DataFrame, p: SketchParams, group: Sequence[str], mode: str = "exact", step: int = 0) -> DataFrame:
    """Cell by cell sum of two sketches. 'exact' keeps the law of independent counters; 'round'
    keeps each mean; 'round_common' shares one draw among the cells of a group, so that the
    least state keeps the bracket of correlated counters."""
    if mode not in ("exact", "round", "round_common"):
        raise ValueError("unknown merge")
    at = [*group, "i", "col"]
    both = a.select(*at, F.col("state").alias("x")).join(b.select(*at, F.col("state").alias("y")), at, "full")
    x, y = (F.coalesce(c, F.lit(0)).cast("int") for c in ("x", "y"))
    own = [F.col(g) for g in group]
    cap = min(p.cap, 1023)
    if mode == "exact":
        state = merge_exact_col(x, y, lambda j: uniform("mg", p.seed, *own, F.col("i"), F.col("col"), step, j), p.base, cap)
    else:
        cell = [] if mode == "round_common" else [F.col("i"), F.col("col")]
        state = merge_round_col(x, y, uniform("mg", p.seed, *own, *cell, step), p.base, cap)
    return both.select(*at, state.cast("int").alias("state"))


def advance_keys(states: np.ndarray, at: np.ndarray, n: np.ndarray, p: SketchParams, seed: int, ids: np.ndarray) -> None:
    """Bulk increments of correlated counters, in place: states is flat, at[l, m] the cells of m
    keys, n their counts. Keys that share a cell take turns. A key jumps by a geometric wait to
    the next draw that moves its least cell; that draw decides for all its cells."""
    order = np.arange(at.shape[1])
    lead = np.empty(len(states), np.int64)
    small = p.cap <= 4095
    chances, slow = (p.base ** -np.arange(p.cap + 1.0), stays(p.base, p.cap)) if small else (None, None)
    while len(order):
        # the first key at each of its cells may go now: of keys written to one cell the last stays
        for row in at:
            lead[row[order[::-1]]] = order[::-1]
        now = np.all([lead[row[order]] == order for row in at], axis=0)
        go, order = order[now], order[~now]
        own, left = states[at[:, go]].astype(np.int64), n[go].astype(np.int64).copy()
        live = np.flatnonzero(left > 0)
        while len(live):
            here, ids_, left_ = own[:, live], ids[go[live]], left[live]
            least = here.min(0)
            chance = chances[least] if small else p.base ** -least.astype(float)
            wait, some = np.ones(len(live)), np.flatnonzero(least > 0)
            if len(some):
                u = mixed(seed, ids_[some], left_[some], 1)
                wait[some] = np.ceil(np.log(u) / (slow[least[some]] if small else np.log1p(-np.minimum(chance[some], 1 - 1e-16))))
            moves = (wait <= left_) & (least < p.cap)
            if p.rule == "conservative":
                rise = here == least
            else:
                # a cell at the least state rises whatever the draw
                rise, higher = here < p.cap, np.flatnonzero((here > least).any(0))
                r, up = mixed(seed, ids_[higher], left_[higher], 2), here[:, higher]
                rise[:, higher] &= r * chance[higher] < (chances[up] if small else p.base ** -up.astype(float))
            own[:, live] += rise & moves
            left[live] = np.where(moves, left_ - wait, 0).astype(np.int64)
            live = live[left[live] > 0]
        for row, values in zip(at, own):
            states[row[go]] = values


def built(counts: np.ndarray, keys: np.ndarray, component: np.ndarray, components: int, p: SketchParams, seed: int) -> np.ndarray:
    """Flat states, or exact cells, [i, col, component] of counts of (component, key), in numpy."""
    size = p.l * p.w * components

    def cells_of(i: int, own: slice) -> np.ndarray:
        k = component[own]
        return (i * p.w + hash_np(keys[own], i, p, k if p.hash_scope == "per_component" else None)) * components + k

    if p.counter == "correlated":
        states = np.zeros(size, np.uint8 if p.bits == 8 else np.int32)
        # keys take turns in order, so parts of them, one after another, end in the same states
        for own in _slices(len(keys)):
            at = np.stack([cells_of(i, own) for i in range(p.l)])
            advance_keys(states, at, counts[own], p, seed, keys[own] * np.int64(components) + component[own])
        return states
    cells = np.zeros(size, np.int64)
    for i in range(p.l):
        cells += np.bincount(cells_of(i, slice(None)), counts, size).astype(np.int64)
    if p.counter == "exact":
        return np.minimum(cells, p.cap).astype(np.int32 if p.bits <= 32 else np.int64)
    some = np.flatnonzero(cells)
    out = np.zeros(size, np.uint8 if p.bits == 8 else np.int32)
    for own in _slices(len(some)):
        at = some[own]
        out[at] = advance(np.zeros(len(at), np.int64), cells[at], p.base, p.cap, seed, at)
    return out


def _slices(n: int, size: int = 1 << 18) -> list[slice]:
    """Parts whose arrays stay small: a worker holds a dozen of them at a time."""
    return [slice(a, a + size) for a in range(0, n, size)]


def joined(a: np.ndarray, b: np.ndarray, p: SketchParams, seed: int, step: int, components: int) -> np.ndarray:
    """Sum of two flat sketches as the sampler merges them: exact cells add; independent counters
    keep their law; correlated ones round with one draw for each component."""
    if p.counter == "exact":
        return np.minimum(a.astype(np.int64) + b, p.cap).astype(a.dtype)
    both = np.flatnonzero((a > 0) & (b > 0))
    out = np.maximum(a, b)
    if p.counter == "independent":
        out[both] = merge_exact(a[both], b[both], p.base, p.cap, seed + step, both)
    else:
        u = mixed(seed, np.arange(components), step)
        out[both] = merge_round(a[both].astype(np.int64), b[both].astype(np.int64), u[both % components], p.base, p.cap)
    return out
