"""All combinations of the ways below two children of a node, or of a node and the ways below its one child, with one
equality tested on each combination.

Rows of the node and of both sides are dealt to cells by a hash of the two classes, a side's rows to a row or a column of
cells. A cell's task compares every row of the one class with every row of the other, a block at a time and on numbers
that stand for the values: as many comparisons as a search makes rows, but only the equal ones become rows.
A class lies in one row or column of cells whole, so a class of most rows makes a few cells large.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from congraph.sources.shipping import ship_code

#: Rows of a side, and combinations, that are compared at a time.
BLOCK, PAIRS = 1 << 16, 1 << 20
#: Nodes of one class to the left whose rows to the right lie together at a time.
NODES = 256
#: Rows of the nodes that a cell is to hold on average.
CELL_ROWS = 600_000


#: Flags that are looked at as one before each of them is.
LINE = 2048


def _bits(values: np.ndarray) -> np.ndarray:
    """16 bits of each value: of all pairs these are compared first, and the values where they agree."""
    return (values.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(48)).astype(np.uint16)


def _set(flags: np.ndarray) -> np.ndarray:
    """Places of the flags that are set."""
    if len(flags) % LINE:
        return np.flatnonzero(flags)
    lines = flags.reshape(-1, LINE)
    some = np.flatnonzero(lines.any(axis=1))
    at = np.flatnonzero(lines[some])
    return some[at // LINE] * LINE + at % LINE


def _equal(a: np.ndarray, b: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places of equal values, from comparing all of a with all of b."""
    short_a, short_b = _bits(a), _bits(b)
    for j in range(0, len(b), BLOCK):
        right = short_b[j : j + BLOCK]
        step = max(1, PAIRS // len(right))
        same = np.empty((min(step, len(a)), len(right)), bool)
        for i in range(0, len(a), step):
            left = short_a[i : i + step]
            np.equal(left[:, None], right[None, :], out=same[: len(left)])
            hit = _set(same[: len(left)].reshape(-1))
            if len(hit):
                x, y = i + hit // len(right), j + hit % len(right)
                if (real := a[x] == b[y]).any():
                    yield x[real], y[real]


def _grouped(classes: np.ndarray) -> tuple[np.ndarray, dict[int, tuple[int, int]]]:
    """(order by class, first and last place of each class in that order)."""
    order = np.argsort(classes, kind="stable")
    values, first = np.unique(classes[order], return_index=True)
    last = np.append(first[1:], len(classes))
    return order, {int(v): (int(a), int(z)) for v, a, z in zip(values, first, last)}


def _matches(left_of: np.ndarray, right_of: np.ndarray, left_class: np.ndarray, left: np.ndarray, right_class: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Numbers of (node, left row, right row) of equal values; left_of, right_of: the classes below each node."""
    codes = np.unique(np.concatenate([left, right]), return_inverse=True)[1].astype(np.int32)
    lorder, lplace = _grouped(left_class)
    rorder, rplace = _grouped(right_class)
    lcodes, rcodes = codes[: len(left)][lorder], codes[len(left) :][rorder]
    norder, nplace = _grouped(left_of)
    found: tuple[list, list, list] = ([], [], [])
    for cls, (a, z) in nplace.items():
        if cls not in lplace:
            continue
        la, lz = lplace[cls]
        nodes = norder[a:z]
        for some in range(0, len(nodes), NODES):
            own = [(n, rplace[c]) for n, c in zip(nodes[some : some + NODES].tolist(), right_of[nodes[some : some + NODES]].tolist()) if c in rplace]
            if not own:
                continue
            first = np.array([x for _, (x, _) in own])
            begin = np.cumsum([0] + [y - x for _, (x, y) in own])
            for i, j in _equal(lcodes[la:lz], np.concatenate([rcodes[x:y] for _, (x, y) in own])):
                k = np.searchsorted(begin, j, side="right") - 1
                for out, rows in zip(found, (np.array([n for n, _ in own])[k], lorder[la + i], rorder[first[k] + j - begin[k]])):
                    out.append(rows)
    return tuple(np.concatenate(x) if x else np.zeros(0, np.int64) for x in found)


def crossed(nodes: DataFrame, left: DataFrame, right: DataFrame, on: tuple[str, str], equal: tuple[str, str], size: int) -> DataFrame:
    """Columns of all three, of long, for each combination of a node, a row of left and a row of right under its two classes
    (`on`, which names a column of nodes and of that side) whose two columns `equal` are equal. size: rows of nodes."""
    spark = nodes.sparkSession
    ship_code(spark)
    side = max(1, round((max(size / CELL_ROWS, spark.sparkContext.defaultParallelism)) ** 0.5))
    names = [nodes.columns, left.columns, right.columns]
    width = max(map(len, names))
    hashed = lambda c: F.pmod(F.xxhash64(c), F.lit(side)).cast("int")
    every = F.explode(F.array(*[F.lit(k) for k in range(side)]))
    none = F.lit(None).cast("long")

    def dealt(df: DataFrame, kind: int, row, column) -> DataFrame:
        held = [F.col(c).alias(f"c{k}") for k, c in enumerate(df.columns)] + [none.alias(f"c{k}") for k in range(len(df.columns), width)]
        return df.select(row.alias("_row"), column.alias("_column"), *held).select((F.col("_row") * side + F.col("_column")).alias("cell"), F.lit(kind).alias("kind"), *[f"c{k}" for k in range(width)])

    a, b = on
    x, y = equal
    rows = dealt(nodes.where(F.col(a).isNotNull() & F.col(b).isNotNull()), 0, hashed(a), hashed(b))
    rows = rows.unionByName(dealt(left.where(F.col(a).isNotNull() & F.col(x).isNotNull()), 1, hashed(a), every))
    rows = rows.unionByName(dealt(right.where(F.col(b).isNotNull() & F.col(y).isNotNull()), 2, every, hashed(b)))
    kept = [names[0], [c for c in names[1] if c != a], [c for c in names[2] if c != b]]
    # Places of what is compared, and of what comes out.
    keys = (names[0].index(a), names[0].index(b), names[1].index(a), names[1].index(x), names[2].index(b), names[2].index(y))
    out = [[(c, own.index(c)) for c in some] for own, some in zip(names, kept)]

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list] = [[], [], []]
        for batch in batches:
            kinds = batch.column("kind").to_numpy()
            for kind in range(3):
                if len(at := np.flatnonzero(kinds == kind)):
                    held[kind].append(batch.select([f"c{k}" for k in range(len(names[kind]))]).take(pa.array(at)))
        if not all(held):
            return
        tables = [pa.Table.from_batches(h).combine_chunks() for h in held]
        column = lambda kind, k: tables[kind].column(k).to_numpy()
        found = _matches(column(0, keys[0]), column(0, keys[1]), column(1, keys[2]), column(1, keys[3]), column(2, keys[4]), column(2, keys[5]))
        got = {c: tables[kind].column(k).take(pa.array(found[kind])) for kind, some in enumerate(out) for c, k in some}
        yield from pa.table(got).to_batches(10_000)

    schema = ", ".join(f"`{c}` long" for some in kept for c in some)
    return rows.repartitionById(side * side, "cell").mapInArrow(compare, schema)


#: Rows of a side that a cell of `paired` is to hold, and combinations up to which groups are enumerated together.
SIDE_ROWS, FEW = 1 << 17, 1 << 12


def class_pairs(nodes: DataFrame, side: DataFrame, on: str) -> DataFrame:
    """Each class of `on` with what `paired` divides its rows of nodes (p) and of side (q) into, and its combinations (pairs)."""
    count = lambda df, n: df.where(F.col(on).isNotNull()).groupBy(on).agg(F.count(F.lit(1)).alias(n))
    parts = lambda n: F.ceil(F.col(n) / F.lit(SIDE_ROWS)).cast("int")
    both = count(nodes, "_n").join(count(side, "_m"), on)
    return both.select(on, parts("_n").alias("_p"), parts("_m").alias("_q"), (F.col("_n") * F.col("_m")).alias("_pairs"))


def _cells(left: list[np.ndarray], right: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order of left, order of right, rows of: first and last place of a cell in both orders) for cells that both sides have."""
    keys = [np.concatenate(x) for x in zip(left, right)]
    order = np.lexsort(keys)
    fresh = np.zeros(len(order), bool)
    for k in keys:
        fresh[1:] |= k[order][1:] != k[order][:-1]
    cell = np.empty(len(order), np.int64)
    cell[order] = np.cumsum(fresh)
    a, b = cell[: len(left[0])], cell[len(left[0]) :]
    oa, ob = np.argsort(a, kind="stable"), np.argsort(b, kind="stable")
    every = np.arange(int(fresh.sum()) + 1)
    spans = np.stack([np.searchsorted(x, every, side=s) for x in (a[oa], b[ob]) for s in ("left", "right")], axis=1)
    return oa, ob, spans[(spans[:, 0] < spans[:, 1]) & (spans[:, 2] < spans[:, 3])]


def _pairs(x: np.ndarray, y: np.ndarray, spans: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places of equal values of x and y within the cells; every combination in a cell is compared."""
    n, m = spans[:, 1] - spans[:, 0], spans[:, 3] - spans[:, 2]
    for a, z, b, w in spans[n * m > FEW].tolist():
        for i, j in _equal(x[a:z], y[b:w]):
            yield a + i, b + j
    small = np.flatnonzero(n * m <= FEW)
    ends = np.cumsum(n[small] * m[small])
    for at in range(0, int(ends[-1]) if len(ends) else 0, PAIRS):
        place = np.arange(at, min(at + PAIRS, int(ends[-1])))
        k = np.searchsorted(ends, place, side="right")
        g, place = small[k], place - (ends[k] - n[small[k]] * m[small[k]])
        i, j = spans[g, 0] + place // m[g], spans[g, 2] + place % m[g]
        if (hit := x[i] == y[j]).any():
            yield i[hit], j[hit]


def paired(nodes: DataFrame, side: DataFrame, on: str, equal: tuple[str, str], classes: DataFrame, cells: int) -> DataFrame:
    """Columns of both, of long, for each combination of a row of nodes and a row of side under its class (`on`, a column of both)
    whose two columns `equal` are equal. classes: what `class_pairs` gives; cells: how many they are cut into. A class of many
    rows is cut into blocks of both sides; a block of the one meets each of the other once."""
    ship_code(nodes.sparkSession)
    names = [nodes.columns, side.columns]
    width = max(map(len, names))

    def dealt(df: DataFrame, kind: int, own: str, other: str) -> DataFrame:
        value = equal[kind]
        df = df.where(F.col(on).isNotNull() & F.col(value).isNotNull()).join(classes.select(on, "_p", "_q"), on)
        df = df.withColumn("_own", F.pmod(F.xxhash64(*names[kind]), F.col(own)).cast("int")).withColumn("_other", F.explode(F.sequence(F.lit(0), F.col(other) - 1)))
        row, column = ("_own", "_other") if kind == 0 else ("_other", "_own")
        held = [F.col(c).alias(f"c{k}") for k, c in enumerate(names[kind])] + [F.lit(None).cast("long").alias(f"c{k}") for k in range(len(names[kind]), width)]
        return df.select(F.lit(kind).cast("byte").alias("kind"), F.col(on).alias("_class"), F.col(row).alias("_row"), F.col(column).alias("_column"), *held)

    rows = dealt(nodes, 0, "_p", "_q").unionByName(dealt(side, 1, "_q", "_p"))
    out = [(0, c, k) for k, c in enumerate(names[0])] + [(1, c, k) for k, c in enumerate(names[1]) if c != on]
    at = [names[kind].index(c) for kind, c in enumerate(equal)]

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list] = [[], []]
        for batch in batches:
            kinds = batch.column("kind").to_numpy()
            for kind in range(2):
                if len(own := np.flatnonzero(kinds == kind)):
                    held[kind].append(batch.select(["_class", "_row", "_column", *(f"c{k}" for k in range(len(names[kind])))]).take(pa.array(own)))
        if not all(held):
            return
        tables = [pa.Table.from_batches(h).combine_chunks() for h in held]
        held.clear()
        keys = [[t.column(k).to_numpy() for k in range(3)] for t in tables]
        oa, ob, spans = _cells(*keys)
        x, y = (t.column(3 + k).to_numpy()[o] for t, k, o in zip(tables, at, (oa, ob)))
        for i, j in _pairs(x, y, spans):
            found = oa[i], ob[j]
            yield pa.RecordBatch.from_arrays([tables[kind].column(3 + k).take(pa.array(found[kind])).combine_chunks() for kind, _, k in out], names=[c for _, c, _ in out])

    # Twice the cells, so that few lie together.
    parts = max(int(nodes.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(2 * cells, 10_000))
    return rows.repartition(parts, "_class", "_row", "_column").mapInArrow(compare, ", ".join(f"`{c}` long" for _, c, _ in out))
