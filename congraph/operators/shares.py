"""One shuffle: rows are dealt to the cells of a hypercube of variable shares, and each cell runs a local
generic join on tries. Every assignment hashes to one cell, so cells give disjoint rows.

A heavy value of a variable fills its cells; `shares_join` is for inputs without one, as the planner's default
strategies are the others. There are at least `cells`, more where they would hold too many rows. A cell's rows are one task's,
as Arrow columns; slices of them by the first variable become tries, which are arrays too, one after the other. Where all
cells hold more than `DEALT_ROWS` together, they are dealt and joined in parts.
"""

from __future__ import annotations

from collections.abc import Iterator, Mapping, Sequence
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from congraph.checkpoints import cut_parts
from congraph.operators.atoms import Frames
from congraph.plans.compile import ConjunctiveQuery
from congraph.plans.order import VarGroup
from congraph.sources.shipping import ship_code


def choose_shares(cq: ConjunctiveQuery, sizes: Mapping[str, int], cells: int) -> dict[str, int]:
    """Doubles the share that adds the least replicated rows, while the cells last; isolated variables stay at 1."""
    names = [v for v in cq.vars if len(cq.containing(v)) > 1]
    shares = dict.fromkeys(cq.vars, 1)

    def moved(s):
        return sum(sizes[a.alias] * reduce(lambda x, v: x * (1 if v in a.vars else s[v]), names, 1) for a in cq.atoms)

    total = 1
    while names and total * 2 <= cells:
        best = min(names, key=lambda v: (moved(shares | {v: shares[v] * 2}), v))
        shares[best] *= 2
        total *= 2
    return shares


class _Trie:
    """Levels of a relation's distinct prefixes, as arrays. A node of depth d + 1 is a place in `value[d]`; the nodes under node i
    of depth d are the places from first[d][i] to first[d][i + 1]. A kind of trie says how it is built and how a value is found."""

    top = (0, 0)

    def __init__(self, rows: Sequence[tuple], width: int):
        self.first: list[np.ndarray] = []
        self.value: list[np.ndarray] = []
        self.build([np.fromiter((r[k] for r in rows), np.int64, len(rows)) for k in range(width)])

    @classmethod
    def of(cls, columns: Sequence[np.ndarray]):
        out = cls((), 0)
        out.build(columns)
        return out

    def build(self, columns: Sequence[np.ndarray]) -> None:
        raise NotImplementedError

    def find(self, depth: int, nodes: np.ndarray, values: np.ndarray) -> np.ndarray:
        """The node under each node that has the value beside it, -1 for none."""
        raise NotImplementedError

    def counts(self, depth: int, nodes: np.ndarray) -> np.ndarray:
        return self.first[depth][nodes + 1] - self.first[depth][nodes]

    def values(self, node) -> Iterator[int]:
        depth, at = node
        yield from self.value[depth][self.first[depth][at] : self.first[depth][at + 1]].tolist() if depth < len(self.value) else ()

    def count(self, node) -> int:
        depth, at = node
        return int(self.first[depth][at + 1] - self.first[depth][at]) if depth < len(self.value) else 0

    def step(self, node, value):
        depth, at = node
        found = int(self.find(depth, np.array([at]), np.array([value]))[0])
        return (depth + 1, found) if found >= 0 else None


class HashTrie(_Trie):
    """A hash table for each level, from a node and a value to the node below."""

    def build(self, columns: Sequence[np.ndarray]) -> None:
        self.parent: list[np.ndarray] = []
        self.table: list[np.ndarray] = []
        above, n_above = np.zeros(len(columns[0]) if columns else 0, np.int32), 1
        for column in columns:
            bits = max(1, int(3 * len(column) // 2).bit_length())
            table, own = np.full(1 << bits, -1, np.int32), np.empty(len(column), np.int32)
            slot, todo = _slots(above, column, bits), np.arange(len(column))
            while len(todo):
                at = slot[todo]
                free = table[at] < 0
                table[at[free]] = todo[free]
                held = table[at]
                same = (above[held] == above[todo]) & (column[held] == column[todo])
                own[todo[same]] = held[same]
                todo = todo[~same]
                slot[todo] = slot[todo] + 1 & (1 << bits) - 1
            # The rows that stand for a node, in order of the node above.
            rows = np.flatnonzero(own == np.arange(len(column)))
            rows = rows[np.argsort(above[rows], kind="stable")]
            place = np.empty(len(column), np.int32)
            place[rows] = np.arange(len(rows))
            taken = table >= 0
            table[taken] = place[table[taken]]
            self.first.append(np.concatenate([[0], np.cumsum(np.bincount(above[rows], minlength=n_above))]).astype(np.int32))
            self.value.append(column[rows])
            self.parent.append(above[rows])
            self.table.append(table)
            above, n_above = place[own], len(rows)

    def find(self, depth: int, nodes: np.ndarray, values: np.ndarray) -> np.ndarray:
        table, parent, value = self.table[depth], self.parent[depth], self.value[depth]
        out = np.full(len(nodes), -1, np.int64)
        todo, slot = np.arange(len(nodes)), _slots(nodes, values, len(table).bit_length() - 1)
        while len(todo):
            held = table[slot]
            some = held >= 0
            todo, slot, held = todo[some], slot[some], held[some]
            same = (parent[held] == nodes[todo]) & (value[held] == values[todo])
            out[todo[same]] = held[same]
            todo, slot = todo[~same], slot[~same] + 1 & len(table) - 1
        return out


def _slots(nodes: np.ndarray, values: np.ndarray, bits: int) -> np.ndarray:
    h = values.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + nodes.astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)
    h = (h ^ h >> np.uint64(32)) * np.uint64(0xD6E8FEB86659FD93)
    return (h >> np.uint64(64 - bits)).astype(np.int64)


class SortedTrie(_Trie):
    """Sorted rows; a value is found by halving the range of its node."""

    def build(self, columns: Sequence[np.ndarray]) -> None:
        order = np.lexsort(columns[::-1]) if columns else np.zeros(0, np.int64)
        fresh, above = np.zeros(len(order), bool), np.zeros(1, np.int64)
        fresh[:1] = True
        for column in columns:
            column = column[order]
            fresh[1:] |= column[1:] != column[:-1]
            starts = np.flatnonzero(fresh)
            self.first.append(np.append(np.searchsorted(starts, above), len(starts)).astype(np.int32))
            self.value.append(column[starts])
            above = starts

    def find(self, depth: int, nodes: np.ndarray, values: np.ndarray) -> np.ndarray:
        value, end = self.value[depth], self.first[depth][nodes + 1]
        if depth == 0:
            low = np.searchsorted(value, values)
        else:
            low, high = self.first[depth][nodes], end
            for _ in range(int((high - low).max(initial=0)).bit_length()):
                middle = low + high >> 1
                less = (low < high) & (value[np.minimum(middle, len(value) - 1)] < values)
                low, high = np.where(less, middle + 1, low), np.where(less, high, middle)
        inside = low < end
        return np.where(inside & (value[np.where(inside, low, 0)] == values) if len(value) else False, low, -1)


#: Values that a round of the local join tries at a time.
TRIED = 1 << 16


def trie_of(names: Sequence[str], columns: Sequence[np.ndarray], order: Sequence[str], trie=HashTrie) -> tuple[list[str], _Trie]:
    """An atom's variables in the order of all, and its trie in that order."""
    cols = [v for v in order if v in names]
    return cols, trie.of([columns[names.index(v)] for v in cols])


def column_join(made: Sequence[tuple[Sequence[str], _Trie]], order: Sequence[str]) -> Iterator[list[np.ndarray]]:
    """Generic join in memory over what `trie_of` gives for each atom; columns by variable, some rows at a time. A round binds a
    variable of many prefixes together; each prefix takes its values from the atom that has the fewest for it."""
    holders = [[i for i, (cols, _) in enumerate(made) if v in cols] for v in order]

    def walk(depth: int, nodes: list[np.ndarray], chosen: list[np.ndarray]) -> Iterator[list[np.ndarray]]:
        if depth == len(order):
            yield chosen
            return
        at = holders[depth]
        level = {i: made[i][0].index(order[depth]) for i in at}
        counts = [made[i][1].counts(level[i], nodes[i]) for i in at]
        least = np.argmin(counts, axis=0)
        for g, i in enumerate(at):
            rows = np.flatnonzero((least == g) & (counts[g] > 0))
            ends = np.cumsum(counts[g][rows])
            first, value = made[i][1].first[level[i]], made[i][1].value[level[i]]
            for a in range(0, int(ends[-1]) if len(ends) else 0, TRIED):
                places = np.arange(a, min(a + TRIED, int(ends[-1])))
                k = np.searchsorted(ends, places, side="right")
                src = rows[k]
                found = {i: first[nodes[i][src] + 1] - (ends[k] - places)}
                values = value[found[i]]
                for j in at:
                    if j != i:
                        below = made[j][1].find(level[j], nodes[j][src], values)
                        if not (hit := below >= 0).all():
                            src, values, below = src[hit], values[hit], below[hit]
                            found = {x: n[hit] for x, n in found.items()}
                        found[j] = below
                if len(src):
                    yield from walk(depth + 1, [found[x] if x in found else n[src] for x, n in enumerate(nodes)], [*(c[src] for c in chosen), values])

    yield from walk(0, [np.zeros(1, np.int64) for _ in made], [])


def local_join(atoms: Sequence[tuple[Sequence[str], Sequence[tuple]]], order: Sequence[str], trie=HashTrie) -> Iterator[tuple]:
    """`column_join` over (variables, rows) of each atom; rows in the order of variables."""
    columns = [(names, [np.fromiter((r[k] for r in rows), np.int64, len(rows)) for k in range(len(names))]) for names, rows in atoms]
    for found in column_join([trie_of(n, c, order, trie) for n, c in columns], order):
        yield from zip(*(c.tolist() for c in found))


#: Rows that a cell is meant to hold, as columns of numbers, and those that its local join holds in tries at a time.
CELL_ROWS, HELD_ROWS = 7_000_000, 500_000
#: Rows dealt to cells in one shuffle; beyond, cells are joined in parts, one after the other.
DEALT_ROWS = 100_000_000


def dealt(cq: ConjunctiveQuery, sizes: Mapping[str, int], shares: Mapping[str, int]) -> int:
    """Rows that all cells hold together."""
    return sum(sizes[a.alias] * reduce(lambda n, v: n * (1 if v in a.vars else shares[v]), shares, 1) for a in cq.atoms)


def fitting_shares(cq: ConjunctiveQuery, sizes: Mapping[str, int], cells: int) -> dict[str, int]:
    """Shares of at least so many cells; of more while a cell has too many rows and twice the cells would leave it clearly fewer."""
    per_cell = lambda s: dealt(cq, sizes, s) / reduce(lambda n, v: n * s[v], s, 1)
    shares = choose_shares(cq, sizes, cells)
    while per_cell(shares) > CELL_ROWS and per_cell(more := choose_shares(cq, sizes, cells * 2)) < 0.8 * per_cell(shares):
        shares, cells = more, cells * 2
    return shares


def cell_slices(names: Sequence[Sequence[str]], held: Sequence[pa.Table], first: str, rows: int) -> Iterator[list[pa.Table]]:
    """The atoms of a cell in slices of about so many rows by the value of one variable. An atom without it keeps what the
    slice can meet: the values of a variable that it shares with an atom already cut down."""
    n = max(1, -(-sum(t.num_rows for t in held) // rows))
    column = lambda t, v, k: t.column(names[k].index(v)).fill_null(0).to_numpy()
    slots = {k: column(held[k], first, k) % n for k in range(len(held)) if first in names[k]}
    for s in range(n):
        taken = {k: held[k].filter(pa.array(slot == s)) for k, slot in slots.items()}
        while near := [(k, j, v) for k in range(len(held)) if k not in taken for j in taken for v in names[k] if v in names[j]]:
            k, j, v = near[0]
            taken[k] = held[k].filter(pa.array(np.isin(column(held[k], v, k), column(taken[j], v, j))))
        yield [taken.get(k, held[k]) for k in range(len(held))]


def shares_join(cq: ConjunctiveQuery, frames: Frames, order: Sequence[VarGroup], sizes: Mapping[str, int], cells: int = 64, trie: str = "hash") -> DataFrame:
    flat = [v for g in order for v in g]
    shares = fitting_shares(cq, sizes, cells)
    width = max(len(a.distinct) for a in cq.atoms)
    split = [v for v in flat if shares[v] > 1]
    names = [list(a.distinct) for a in cq.atoms]
    kind = {"hash": HashTrie, "sorted": SortedTrie}[trie]
    schema, rows_held = pa.schema([(v, pa.int64()) for v in flat]), HELD_ROWS

    def join_cell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list] = [[] for _ in names]
        for batch in batches:
            which = batch.column("atom").to_numpy()
            for k, own in enumerate(names):
                if len(at := np.flatnonzero(which == k)):
                    some = batch.select([f"c{i}" for i in range(len(own))])
                    held[k].append(some if len(at) == len(which) else some.take(pa.array(at)))
        if not all(held):
            return
        tables = [pa.Table.from_batches(h) for h in held]
        # A null stays only where nothing is to meet it: the column is made places of its values, the last one for null.
        coded: dict[str, pa.Array] = {}
        for k, own in enumerate(names):
            for i, v in enumerate(own):
                if (column := tables[k].column(i)).null_count:
                    coded[v] = pa.concat_arrays([pc.drop_null(pc.unique(column)), pa.nulls(1, pa.int64())])
                    place = pc.index_in(column, value_set=coded[v][:-1]).cast(pa.int64()).fill_null(len(coded[v]) - 1)
                    tables[k] = tables[k].set_column(i, f"c{i}", place)
        held.clear()
        # Slices by the variable whose atoms have the most rows; the tries of the other atoms serve all slices.
        by = max(flat, key=lambda v: sum(t.num_rows for own, t in zip(names, tables) if v in own))
        columns = lambda t: [c.to_numpy() for c in t.columns]
        cut = [k for k, own in enumerate(names) if by in own]
        tries = {k: trie_of(own, columns(tables[k]), flat, kind) for k, own in enumerate(names) if k not in cut}
        tables = [tables[k] for k in cut]
        for part in cell_slices([names[k] for k in cut], tables, by, rows_held):
            if all(t.num_rows for t in part):
                tries |= {k: trie_of(names[k], columns(t), flat, kind) for k, t in zip(cut, part)}
                for found in column_join([tries[k] for k in range(len(names))], flat):
                    made = [coded[v].take(pa.array(c)) if v in coded else pa.array(c, pa.int64()) for v, c in zip(flat, found)]
                    yield pa.RecordBatch.from_arrays(made, schema=schema)

    most = max(split, key=shares.__getitem__) if split else None
    n_parts = min(shares[most], -(-dealt(cq, sizes, shares) // DEALT_ROWS)) if split else 1
    n_cells = reduce(lambda n, v: n * shares[v], shares, 1)

    def dealt_rows(at: int) -> DataFrame:
        """Rows of one part with their cells: those whose place of the variable with the largest share falls to the part."""
        parts = None
        for k, a in enumerate(cq.atoms):
            df, cell = frames[a.alias], F.lit(0)
            # A null meets nothing.
            df = df.where(reduce(lambda x, v: x & F.col(v).isNotNull(), [v for v in a.distinct if len(cq.containing(v)) > 1], F.lit(True)))
            for v in split:
                if v in a.vars:
                    place = F.pmod(F.xxhash64(v, F.lit(v)), F.lit(shares[v])).cast("int")
                    df = df.where(place % n_parts == at) if v == most else df
                else:
                    df = df.withColumn(f"_p_{v}", F.explode(F.sequence(F.lit(at if v == most else 0), F.lit(shares[v] - 1), F.lit(n_parts if v == most else 1))))
                    place = F.col(f"_p_{v}")
                cell = cell * shares[v] + place
            columns = [F.col(v).alias(f"c{i}") for i, v in enumerate(a.distinct)] + [F.lit(None).cast("long").alias(f"c{i}") for i in range(len(a.distinct), width)]
            one = df.select(cell.alias("cell"), F.lit(k).cast("byte").alias("atom"), *columns)
            parts = one if parts is None else parts.unionByName(one)
        return parts

    def joined(at: int) -> DataFrame:
        rows = dealt_rows(at)
        ship_code(rows.sparkSession)
        return rows.repartitionById(n_cells, "cell").drop("cell").mapInArrow(join_cell, ", ".join(f"`{v}` long" for v in flat))

    return cut_parts(map(joined, range(n_parts)), "cells") if n_parts > 1 else joined(0)
