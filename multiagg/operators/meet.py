"""Join on values that are dropped, multiply counts and add up, without handing the product's rows through a shuffle.

Both sides are dealt by the join values and sorted by them within a task. A task takes runs of whole join values,
writes either side as a matrix of counts (its groups by join values) and multiplies these, or pairs the rows
where they are thin. What it gives on is summed for a run already; Spark adds up the runs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from multiagg.operators.algebra import M
from multiagg.operators.graph import DataGraph, added, multiplied

#: Rows of both sides that are multiplied at once; a join value of more rows is taken whole.
RUN_ROWS = 250_000
#: Cells of a matrix, and pairs of rows, that a task makes at once.
CELLS = 4_000_000
#: A multiplication within a matrix costs about so much less than a pair of rows.
DENSE = 50


def fused(graph: DataGraph, left: DataFrame, right: DataFrame, on: list[str], keep: list[str]) -> bool:
    """Counts in long alone; a join value is dropped and both sides bring groups, else there is no more to add up than Spark does well."""
    a = graph.algebra
    counts = a.counts and not a.parts and not a.distinct and graph.spec.count_type == "long" and M in left.columns and M in right.columns
    here = [c for c in keep if c in left.columns]
    return counts and not set(on) <= set(keep) and bool(set(here) - set(on)) and len(here) < len(keep)


def met(graph: DataGraph, left: DataFrame, right: DataFrame, on: list[str], keep: list[str], by_value: tuple[str, ...] = ()) -> DataFrame:
    """`multiplied` and then `added`."""
    keep = list(dict.fromkeys(keep))
    if not fused(graph, left, right, on, keep):
        return added(graph, multiplied(graph, left, right, on, keep, by_value=by_value), keep)
    keys = [*on, *by_value]
    here = [c for c in keep if c in left.columns]
    there = [c for c in keep if c not in here]
    kinds = {f.name: f.dataType for f in [*right.schema, *left.schema]}
    names = [f"k{i}" for i in range(len(keys))]

    def side(df: DataFrame, which: int) -> DataFrame:
        own = [F.col(c) if (c in here) == (which == 0) else F.lit(None).cast(kinds[c]) for c in keep]
        return df.select(*(F.col(c).cast(kinds[c]).alias(k) for c, k in zip(keys, names)), F.lit(which).alias("side"), *(x.alias(f"c{i}") for i, x in enumerate(own)), F.col(M).alias("m"))

    both = side(left, 0).unionAll(side(right, 1)).repartition(*names).sortWithinPartitions(*names, "side")
    schema = ", ".join(f"`{c}` {kinds[c].simpleString()}" for c in [*keep, M])
    return added(graph, both.mapInArrow(_multiplier(names, [f"c{keep.index(c)}" for c in here], [f"c{keep.index(c)}" for c in there], [*here, *there], keep), schema), keep)


def _multiplier(names: list[str], here: list[str], there: list[str], made: list[str], keep: list[str]):
    """The task's function. It refers to nothing of this package, which workers need not have."""
    run_rows, cells, dense, count = RUN_ROWS, CELLS, DENSE, M

    def codes(column: pa.ChunkedArray) -> tuple[np.ndarray, pa.Array]:
        d = column.combine_chunks().dictionary_encode(null_encoding="encode")
        d = d.combine_chunks() if isinstance(d, pa.ChunkedArray) else d
        return d.indices.to_numpy(zero_copy_only=False).astype(np.int64), d.dictionary

    def grouped(t: pa.Table, cols: list[str]) -> tuple[np.ndarray, list[pa.Array]]:
        """A number for each row's group, and the groups' values."""
        number, values = np.zeros(t.num_rows, np.int64), []
        for c in cols:
            code, words = codes(t.column(c))
            seen, number = np.unique(number * max(len(words), 1) + code, return_inverse=True)
            earlier, last = np.divmod(seen, max(len(words), 1))
            values = [v.take(pa.array(earlier)) for v in values] + [words.take(pa.array(last))]
        return number, values

    def exact(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The product of two matrices of counts. Doubles hold whole numbers below 2^53, and no part of a sum is larger than the sum."""
        near = a.astype(np.float64) @ b.astype(np.float64)
        most = near.max(initial=0.0)
        if most < 2.0**53:
            return near.astype(np.int64)
        if most < 2.0**62:
            return a @ b
        out = a.astype(object) @ b.astype(object)
        if out.max() >= 2**63:
            raise ArithmeticError("long overflow")
        return out.astype(np.int64)

    def product(t: pa.Table) -> Iterator[pa.RecordBatch]:
        new = np.zeros(t.num_rows, bool)
        for k in names:
            code, _ = codes(t.column(k))
            new[1:] |= code[1:] != code[:-1]
        key, right = np.cumsum(new), t.column("side").to_numpy() == 1
        n = int(key[-1]) + 1
        nl, nr = np.bincount(key[~right], minlength=n), np.bincount(key[right], minlength=n)
        meets = (nl > 0) & (nr > 0)
        if not meets.any():
            return
        pick = meets[key]
        t, key, right = t.filter(pa.array(pick)), (np.cumsum(meets) - 1)[key[pick]], right[pick]
        nl, nr, n = nl[meets], nr[meets], int(meets.sum())
        l, r = t.filter(pa.array(~right)), t.filter(pa.array(right))
        (lg, lvalues), (rg, rvalues), lk, rk = grouped(l, here), grouped(r, there), key[~right], key[right]
        lm, rm = l.column("m").to_numpy().astype(np.int64), r.column("m").to_numpy().astype(np.int64)
        ln, rn = int(lg.max()) + 1, int(rg.max()) + 1
        pairs = float((nl.astype(float) * nr).sum())

        def out(lo: np.ndarray, ro: np.ndarray, m: np.ndarray) -> Iterator[pa.RecordBatch]:
            for at in range(0, len(m), 1_000_000):
                li, ri = pa.array(lo[at : at + 1_000_000]), pa.array(ro[at : at + 1_000_000])
                table = dict(zip(made, [*(v.take(li) for v in lvalues), *(v.take(ri) for v in rvalues)])) | {count: pa.array(m[at : at + 1_000_000])}
                yield pa.RecordBatch.from_arrays([table[c] for c in [*keep, count]], names=[*keep, count])

        by = np.argsort(lg, kind="stable")
        lg, lk, lm = lg[by], lk[by], lm[by]
        if float(ln) * rn * n <= dense * pairs:
            wide = max(1, cells // max(n, 1))
            for c0 in range(0, rn, wide):
                at = (rg >= c0) & (rg < c0 + wide)
                b = np.zeros((n, min(wide, rn - c0)), np.int64)
                np.add.at(b, (rk[at], rg[at] - c0), rm[at])
                tall = max(1, cells // max(n, b.shape[1]))
                for r0 in range(0, ln, tall):
                    s = slice(*np.searchsorted(lg, [r0, r0 + tall]))
                    a = np.zeros((min(tall, ln - r0), n), np.int64)
                    np.add.at(a, (lg[s] - r0, lk[s]), lm[s])
                    c = exact(a, b)
                    lo, ro = np.nonzero(c)
                    yield from out(lo + r0, ro + c0, c[lo, ro])
            return
        starts = np.concatenate([[0], np.cumsum(nr)])
        many = nr[lk]
        bound = np.concatenate([[0], np.cumsum(many)])
        lo = 0
        while lo < len(lg):
            hi = max(lo + 1, int(np.searchsorted(bound, bound[lo] + cells, "right")) - 1)
            row = np.repeat(np.arange(lo, hi), many[lo:hi])
            other = np.arange(len(row)) - np.repeat(bound[lo:hi] - bound[lo], many[lo:hi]) + starts[lk[row]]
            x, y = lm[row], rm[other]
            near = x.astype(np.float64) * y
            if near.sum() >= 2.0**62:
                x, y = x.astype(object), y.astype(object)
            seen, back = np.unique(lg[row] * rn + rg[other], return_inverse=True)
            m = np.zeros(len(seen), x.dtype)
            np.add.at(m, back, x * y)
            if m.dtype == object:
                if max(m) >= 2**63:
                    raise ArithmeticError("long overflow")
                m = m.astype(np.int64)
            yield from out(seen // rn, seen % rn, m)
            lo = hi

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows, rest = [], 0, None
        for b in batches:
            if not b.num_rows:
                continue
            held.append(b)
            rows += b.num_rows
            if rows < run_rows:
                continue
            t = pa.Table.from_batches(held)
            last = np.ones(rows, bool)
            for k in names:
                code, _ = codes(t.column(k))
                last &= code == code[-1]
            first = rows - int(np.argmin(last[::-1])) if not last.all() else 0
            if first:
                yield from product(t.slice(0, first))
            rest = t.slice(first)
            held, rows = rest.to_batches(), rest.num_rows
        if held:
            yield from product(pa.Table.from_batches(held))

    return run
