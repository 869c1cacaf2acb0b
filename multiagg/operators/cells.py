"""Join on values that are dropped with whole sums: groups are dealt instead of join values, so no partial sum is handed on.

`meet` deals join values, and each task then holds a part of every group's sum. Where these parts are many more than
the rows of both sides, groups are dealt instead: blocks of the left side's groups by blocks of the first arm's make a grid,
each of its cells gets the rows of both blocks and all of further arms, and what it gives on are its groups' results.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from math import prod

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from multiagg.operators.algebra import M
from multiagg.operators.graph import DataGraph

#: Rows that a cell may be expected to hold.
CELL_ROWS = 20_000_000
#: Rows that are packed at once before they are dealt.
PACK_ROWS = 500_000
#: Numbers of a matrix, and pairs of rows, that a task makes at once.
CELLS = 8_000_000
#: A multiplication within a matrix costs about so much less than a pair of rows.
DENSE = 400
#: Rows with parts of sums below which they may as well be shuffled.
PARTS = 10_000_000


def grid(sizes: list[float], groups: list[float], tasks: int) -> tuple[float, int, int] | None:
    """Rows dealt and blocks of the left side's and the first arm's groups; `sizes` are rows of all sides. None where a cell would hold too many."""
    left, first, more, made = sizes[0], sizes[1], sum(sizes[2:]), []
    blocks = [1, 2, 3, 4, 6, 8, 12, 16, 24, 32, 48, 64, 96, 128]
    for r in blocks:
        for c in blocks:
            if tasks <= r * c <= 64 * tasks and r <= max(1.0, groups[0] / 8) and c <= max(1.0, groups[1] / 8) and left / r + first / c + more <= CELL_ROWS:
                made.append((left * c + first * r + more * r * c, r, c))
    return min(made, default=None)


def fitting(graph: DataGraph, left, arms: list, on: list[str], here: list[str], there: list[list[str]]) -> tuple[int, int] | None:
    """The grid, where it deals clearly fewer rows than parts of sums would leave the tasks; sides are given as sizes expected."""
    a = graph.algebra
    if not on or not a.counts or a.parts or a.distinct or graph.spec.count_type != "long" or left is None:
        return None
    values = max(x.keys(on) for x in (left, *arms))
    pairs = left.rows * prod(x.rows / max(values, 1.0) for x in arms)
    groups = [x.keys(g) for x, g in zip([left, *arms], [here, *there])]
    tasks = graph.edges[graph.tree.name].sparkSession.sparkContext.defaultParallelism
    parts = min(pairs, prod(groups) * tasks)
    made = reduce(lambda t, x: t.met(x, on, [*t.values, *x.values]), arms, left).collapsed([*here, *(g for gs in there for g in gs)]).rows
    found = grid([left.rows, *(x.rows for x in arms)], groups, tasks)
    dense = prod(groups) * values <= DENSE * pairs and values <= CELLS / 64
    if found is None or pairs < 4 * made or parts < max(PARTS, found[0] / 2) or len(arms) > 1 and not dense:
        return None
    return found[1:]


def met_in_cells(graph: DataGraph, left: DataFrame, arms: list[tuple[DataFrame, list[str]]], on: list[str], keep: list[str], blocks: tuple[int, int], arm_on: list[str] | None = None) -> DataFrame:
    """Left side and arms joined on `on`, counts multiplied and added up by `keep`. Each arm comes with its groups; no two sides share one."""
    keep, (r, c) = list(dict.fromkeys(keep)), blocks
    groups = [[x for x in keep if x not in {y for _, g in arms for y in g}], *(g for _, g in arms)]
    kinds = {f.name: f.dataType for df in (*(a for a, _ in arms), left) for f in df.schema}
    block = lambda cols, n: F.pmod(F.xxhash64(*cols), F.lit(n)) if cols and n > 1 else F.lit(0)
    names = [f"k{j}" for j in range(len(on))]

    def side(df: DataFrame, i: int) -> DataFrame:
        """Rows of a side packed by blocks, and each pack dealt to the cells of its block."""
        own = [F.col(x).alias(f"c{keep.index(x)}") for x in groups[i]]
        rows = df.select(block(groups[i], (r, c)[i] if i < 2 else 1).cast("int").alias("block"), *(F.col(k).cast(kinds[k]).alias(j) for k, j in zip(on, names)), *own, F.col(M).alias("m"))
        packs = rows.mapInArrow(_pack(rows.columns[1:]), "block int, rows binary")
        first, last, step = [("block * {c}", "block * {c} + {c} - 1", 1), ("block", "block + ({r} - 1) * {c}", c), ("0", "{r} * {c} - 1", 1)][min(i, 2)]
        cell = F.expr(f"explode(sequence({first}, {last}, {step}))".format(r=r, c=c))
        return packs.select(cell.alias("cell"), F.lit(i).alias("side"), "rows")

    sides = reduce(DataFrame.unionAll, [side(df, i) for i, df in enumerate([left, *(a for a, _ in arms)])])
    schema = ", ".join(f"`{x}` {kinds[x].simpleString()}" for x in [*keep, M])
    return sides.repartitionById(r * c, F.col("cell")).mapInArrow(_cell(names, [[f"c{keep.index(x)}" for x in g] for g in groups], [x for g in groups for x in g], keep), schema)


def _pack(columns: list[str]):
    """The task's function that writes rows of one block into one value; sorted, they take little room."""
    size = PACK_ROWS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def packed() -> pa.RecordBatch:
            t = pa.Table.from_batches(held)
            t = t.sort_by([(c, "ascending") for c in ["block", *columns[::-1][1:], "m"]]).combine_chunks()
            at = t.column("block").to_numpy()
            bounds = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1], [True]]))
            values = []
            for lo, hi in zip(bounds[:-1], bounds[1:]):
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, t.select(columns).schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as w:
                    w.write_table(t.select(columns).slice(lo, hi - lo).combine_chunks())
                values.append(sink.getvalue().to_pybytes())
            return pa.RecordBatch.from_arrays([pa.array(at[bounds[:-1]], pa.int32()), pa.array(values, pa.binary())], names=["block", "rows"])

        held, rows = [], 0
        for b in batches:
            if b.num_rows:
                held.append(b)
                rows += b.num_rows
            if rows >= size:
                yield packed()
                held, rows = [], 0
        if held:
            yield packed()

    return run


def _cell(names: list[str], groups: list[list[str]], made: list[str], keep: list[str]):
    """The task's function. It refers to nothing of this package, which workers need not have."""
    cells, dense, count, sides = CELLS, DENSE, M, len(groups)

    def codes(column: pa.ChunkedArray) -> tuple[np.ndarray, pa.Array]:
        d = column.combine_chunks().dictionary_encode(null_encoding="encode")
        d = d.combine_chunks() if isinstance(d, pa.ChunkedArray) else d
        return d.indices.to_numpy(zero_copy_only=False).astype(np.int64), d.dictionary

    def grouped(t: pa.Table, cols: list[str]) -> tuple[np.ndarray, list[pa.Array]]:
        """A number for each row's values, and the values."""
        number, values = np.zeros(t.num_rows, np.int64), []
        for c in cols:
            code, words = codes(t.column(c))
            if not values:
                number, values = code, [words]
                continue
            seen, number = np.unique(number * max(len(words), 1) + code, return_inverse=True)
            earlier, last = np.divmod(seen, max(len(words), 1))
            values = [v.take(pa.array(earlier)) for v in values] + [words.take(pa.array(last))]
        return number, values

    def summed(at: np.ndarray, x: np.ndarray, y: np.ndarray | int = 1) -> tuple[np.ndarray, np.ndarray]:
        """Places, each once, and the sums of the products there."""
        if (x.astype(np.float64) * y).sum() >= 2.0**62:
            x = x.astype(object)
        seen, back = np.unique(at, return_inverse=True)
        m = np.zeros(len(seen), x.dtype)
        np.add.at(m, back, x * y)
        return seen, m

    def whole(m: np.ndarray) -> np.ndarray:
        if m.dtype == object and m.max() >= 2**63:
            raise ArithmeticError("long overflow")
        return m.astype(np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[pa.Table]] = [[] for _ in range(sides)]
        for b in batches:
            for i, x in zip(b.column("side").to_pylist(), b.column("rows")):
                held[i].append(pa.ipc.open_stream(x.as_buffer()).read_all())
        if not all(held):
            return
        tables = [pa.concat_tables(x) for x in held]
        held = []
        key, _ = grouped(pa.concat_tables([t.select(names) for t in tables]), names)
        keys = np.split(key, np.cumsum([t.num_rows for t in tables])[:-1])
        n = int(key.max()) + 1
        meets = np.ones(n, bool)
        for k in keys:
            meets &= np.bincount(k, minlength=n) > 0
        if not meets.any():
            return
        number, n = np.cumsum(meets) - 1, int(meets.sum())
        rows, values = [], []  # of each side: group, key and count, ordered by group and key, each pair of them once
        for i in range(sides):
            pick = meets[keys[i]]
            t, k = tables[i].filter(pa.array(pick)), number[keys[i][pick]]
            g, words = grouped(t, groups[i])
            at, m = g * n + k, t.column("m").to_numpy().astype(np.int64)
            by = np.argsort(at, kind="stable")
            at, m = at[by], m[by]
            if (at[1:] == at[:-1]).any():
                at, m = summed(at, m)
            rows.append((at // n, at % n, whole(m)))
            values.append(words)
            tables[i] = None
        (lg, lk, lm), (rg, rk, rm) = rows[0], rows[-1]
        ln, rn = int(lg[-1]) + 1, int(rg[-1]) + 1

        def out(lo: np.ndarray, mid: tuple[int, ...], ro: np.ndarray, m: np.ndarray) -> Iterator[pa.RecordBatch]:
            for at in range(0, len(m), 1_000_000):
                li, ri = pa.array(lo[at : at + 1_000_000]), pa.array(ro[at : at + 1_000_000])
                same = [v.take(pa.array(np.full(len(li), g, np.int64))) for words, g in zip(values[1:-1], mid) for v in words]
                table = dict(zip(made, [*(v.take(li) for v in values[0]), *same, *(v.take(ri) for v in values[-1])])) | {count: pa.array(m[at : at + 1_000_000])}
                yield pa.RecordBatch.from_arrays([table[c] for c in [*keep, count]], names=[*keep, count])

        def between(i: int, ks: np.ndarray, ms: np.ndarray) -> Iterator[tuple[tuple[int, ...], np.ndarray, np.ndarray]]:
            """Groups of the arms from i to the last but one, with the keys that they share and the products of their counts."""
            if i == sides - 1:
                yield (), ks, ms
                return
            g, k, m = rows[i]
            weight = np.zeros(n, object if len(ms) and float(ms.max()) * float(m.max()) >= 2.0**62 else np.int64)
            weight[ks] = ms
            starts = np.flatnonzero(np.concatenate([[True], g[1:] != g[:-1]]))
            for lo, hi in zip(starts, [*starts[1:], len(g)]):
                at = weight[k[lo:hi]] > 0
                if at.any():
                    for mid, kk, mm in between(i + 1, k[lo:hi][at], m[lo:hi][at] * weight[k[lo:hi][at]]):
                        yield (int(g[lo]), *mid), kk, mm

        def filled(g: np.ndarray, k: np.ndarray, m: np.ndarray, lo: int, size: int, kind=np.int64) -> np.ndarray:
            s = slice(*np.searchsorted(g, [lo, lo + size]))
            made = np.zeros((n, size), kind)
            made[k[s], g[s] - lo] = m[s]
            return made

        several = sides > 2
        nl, nr = np.bincount(lk, minlength=n), np.bincount(rk, minlength=n)
        if several or float(ln) * rn * n <= dense * float((nl.astype(float) * nr).sum()):
            tall, wide = min(ln, max(1, cells // n), 2000), min(rn, max(1, cells // n), 2000)
            for r0 in range(0, ln, tall):
                a = filled(lg, lk, lm, r0, min(tall, ln - r0), np.float64)
                for c0 in range(0, rn, wide):
                    b = filled(rg, rk, rm, c0, min(wide, rn - c0), np.float64)
                    for mid, ks, ms in between(1, np.arange(n), np.ones(n, np.int64)):
                        x, y = (a, b) if len(ks) == n else (a[ks], b[ks])
                        c = (x * ms.astype(np.float64)[:, None]).T @ y if several else x.T @ y
                        most = c.max(initial=0.0)
                        if most >= 2.0**53:  # doubles hold whole numbers up to there, and no part of a sum is larger than the sum
                            kind = object if most >= 2.0**62 or ms.dtype == object else np.int64
                            x, y = filled(lg, lk, lm, r0, a.shape[1], kind)[ks], filled(rg, rk, rm, c0, b.shape[1], kind)[ks]
                            c = (x * ms.astype(kind)[:, None]).T @ y
                        c = whole(c)
                        lo, ro = np.nonzero(c)
                        yield from out(lo + r0, mid, ro + c0, c[lo, ro])
            return
        by = np.argsort(rk, kind="stable")
        rg, rk, rm = rg[by], rk[by], rm[by]
        starts, many = np.concatenate([[0], np.cumsum(nr)]), nr[lk]
        bound = np.concatenate([[0], np.cumsum(many)])
        ends = np.concatenate([np.flatnonzero(lg[1:] != lg[:-1]) + 1, [len(lg)]])  # of whole groups
        lo = 0
        while lo < len(lg):
            fits = ends[(ends > lo) & (bound[ends] <= bound[lo] + cells)]
            stop = int(fits[-1]) if len(fits) else int(ends[ends > lo][0])
            sums: list[tuple[np.ndarray, np.ndarray]] = []
            while lo < stop:
                hi = min(stop, max(lo + 1, int(np.searchsorted(bound, bound[lo] + cells, "right")) - 1))
                row = np.repeat(np.arange(lo, hi), many[lo:hi])
                other = np.arange(len(row)) - np.repeat(bound[lo:hi] - bound[lo], many[lo:hi]) + starts[lk[row]]
                sums.append(summed(lg[row] * rn + rg[other], lm[row], rm[other]))
                if len(sums) > 1:
                    sums = [summed(np.concatenate([x for x, _ in sums]), np.concatenate([x for _, x in sums]))]
                lo = hi
            seen, m = sums[0]
            yield from out(seen // rn, (), seen % rn, whole(m))

    return run
