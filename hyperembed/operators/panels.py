"""Averages over hyperedges and back for tables of wide vectors, a few columns (a panel) at a time.

A join sends a row of `width` numbers for every membership through the disk, twice a hop. Here memberships go there once; workers
hold a panel of all nodes' vectors, add up in arrays, and keep panels in files of the shared folder. Vectors of hyperedges are never kept.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..session import work_folder
from .blocks import VEC, rows_of, vec_batch

#: Memberships times width up to which joins do; nodes from which on a worker does not hold a column any more.
JOINED, NODES = 20_000_000, 6_000_000
#: Bytes of a panel in a worker, memberships of a file.
PANEL_BYTES, FILE_ROWS = 56 << 20, 500_000
NUMBERS = pa.schema([("x", pa.float64())])


def _open(folder: str):
    from pyarrow import fs as pafs

    return pafs.FileSystem.from_uri(folder)


def _save(folder: str, name: str, arrays) -> None:
    """Arrays of numbers as one batch each; zeros and repeated values take little room."""
    fs, base = _open(folder)
    with fs.open_output_stream(f"{base}/{name}", compression=None) as out, pa.ipc.new_file(out, NUMBERS, options=pa.ipc.IpcWriteOptions(compression="lz4")) as w:
        for x in arrays:
            w.write_batch(pa.RecordBatch.from_arrays([pa.array(np.asarray(x, np.float64).ravel())], schema=NUMBERS))


def _load(folder: str, name: str, which: int) -> np.ndarray:
    fs, base = _open(folder)
    with fs.open_input_file(f"{base}/{name}") as f, pa.ipc.open_file(f) as r:
        return r.get_batch(which).column(0).to_numpy()


def smooth(rows: DataFrame, vecs: DataFrame, width: int, hops: int) -> DataFrame | None:
    """(id, vec) after `hops` averages over the hyperedges of (eid, vid, gamma, w) and back; None where joins are the better way."""
    size = rows.count()
    if size * width <= JOINED:
        return None
    ids = np.sort(rows.select("vid").distinct().limit(NODES + 1).toArrow().column(0).to_numpy())
    if len(ids) > NODES:
        return None
    return Panels(rows.sparkSession, rows, size, ids, width).after(vecs.where("id is not null and vec is not null"), hops)


class Panels:
    """Memberships and vectors in files, and the ids of all nodes in order."""

    def __init__(self, spark, rows: DataFrame, size: int, ids: np.ndarray, width: int):
        self.spark, self.ids, self.width = spark, ids, width
        self.folder = f"{work_folder(spark)}/graph-panels-{uuid.uuid4().hex}"
        if "://" not in self.folder and not self.folder.startswith("file:"):
            self.folder = f"file://{self.folder}"
        fs, base = _open(self.folder)
        fs.create_dir(base, recursive=True)
        self.columns = max(1, min(width + 1, PANEL_BYTES // (8 * len(ids))))
        # One more column tells which nodes any vector reaches.
        self.panels = -(-(width + 1) // self.columns)
        self.held = spark.sparkContext.broadcast(ids)
        self.files = max(1, -(-size // FILE_ROWS))
        self.groups = min(self.files, max(1, spark.sparkContext.defaultParallelism))
        self.ranges = max(self.groups, -(-len(ids) // 20_000))
        self._store_rows(rows)
        self._store_degrees()

    def _job(self, tasks: int, run) -> list:
        """`run(i)` for each task on executors; what it returns (a string)."""

        def each(batches):
            for b in batches:
                for i in b.column(0).to_pylist():
                    yield pa.RecordBatch.from_pydict({"made": [str(run(i))]})

        made = [r[0] for r in self.spark.range(0, tasks, 1, tasks).mapInArrow(each, "made string").collect()]
        if len(made) != tasks:
            raise RuntimeError(f"{len(made)} tasks of {tasks} gave a result")
        return made

    def _store_rows(self, rows: DataFrame) -> None:
        """A file for each share of the hyperedges: their sizes, then places of members, w * gamma, gamma / delta."""
        folder, held = self.folder, self.held

        def run(batches):
            parts = [[np.array(b.column(c).to_numpy()) for c in range(5)] for b in batches if b.num_rows]
            if not parts:
                return
            share, eid, vid, gamma, w = (np.concatenate(x) for x in zip(*parts))
            del parts
            for i in np.unique(share).tolist():
                some = np.flatnonzero(share == i)
                some = some[np.lexsort((vid[some], eid[some]))]
                e, g = eid[some], gamma[some]
                first = np.flatnonzero(np.r_[True, e[1:] != e[:-1]])
                length = np.diff(np.r_[first, len(e)])
                _save(folder, f"rows-{i}", [length, np.searchsorted(held.value, vid[some]), w[some] * g, g / np.repeat(np.add.reduceat(g, first), length)])
                yield pa.RecordBatch.from_pydict({"share": [int(i)]})

        shared = rows.withColumn("share", F.pmod(F.xxhash64("eid"), F.lit(self.files)).cast("int")).select("share", "eid", "vid", "gamma", "w")
        made = shared.repartition(self.files, "share").mapInArrow(run, "share long").collect()
        self.shares = sorted(r[0] for r in made)

    def _store_vectors(self, vecs: DataFrame) -> list[str]:
        """Names of files with the places of some nodes, then a panel's columns of their vectors for each panel."""
        folder, held, width, columns, panels = self.folder, self.held, self.width, self.columns, self.panels

        def run(batches):
            for b in batches:
                at = np.searchsorted(held.value, b.column("id").to_numpy())
                known = held.value[np.minimum(at, len(held.value) - 1)] == b.column("id").to_numpy()
                if known.any():
                    at, inside = np.unique(at[known], return_inverse=True)
                    x = np.zeros((len(at), width + 1))
                    np.add.at(x, inside, np.hstack([rows_of(b)[known], np.ones((len(inside), 1))]))
                    x, name = x.T, f"given-{uuid.uuid4().hex}"
                    _save(folder, name, [at, *(x[p * columns:(p + 1) * columns] for p in range(panels))])
                    yield pa.RecordBatch.from_pydict({"name": [name]})

        return [r[0] for r in vecs.select("id", F.slice("vec", 1, width).alias("vec")).mapInArrow(run, "name string").collect()]

    def _store_degrees(self) -> None:
        folder, held, groups, shares = self.folder, self.held, self.groups, self.shares

        def run(g):
            d = np.zeros(len(held.value))
            for i in shares[g::groups]:
                d += np.bincount(_load(folder, f"rows-{i}", 1).astype(np.int64), _load(folder, f"rows-{i}", 2), len(d))
            _save(folder, f"degrees-{g}", [d])

        self._job(groups, run)

    def _hop(self, names: list[str], panel: int, given: bool, label: str) -> list[str]:
        """Each group of hyperedges gives its part of the sums; the next reader adds the parts up and divides by degrees."""
        folder, groups, shares, read = self.folder, self.groups, self.shares, self._reader(panel)

        def run(g):
            x = read(names, given)
            out = np.zeros_like(x)
            for i in shares[g::groups]:
                length, to, up, down = (_load(folder, f"rows-{i}", k) for k in range(4))
                length, to = length.astype(np.int64), to.astype(np.int64)
                first = np.cumsum(length) - length
                for column, total in zip(x, out):
                    middle = np.add.reduceat(np.take(column, to) * down, first)
                    total += np.bincount(to, np.repeat(middle, length) * up, len(total))
            _save(folder, f"{label}-{g}", out)
            return f"{label}-{g}"

        return self._job(groups, run)

    def _reader(self, panel: int):
        folder, held, groups = self.folder, self.held, self.groups
        width = min(self.columns, self.width + 1 - panel * self.columns)

        def read(names, given, lo=0, hi=None):
            n = len(held.value)
            hi = n if hi is None else hi
            x = np.zeros((width, hi - lo))
            for name in names:
                if given:
                    at = _load(folder, name, 0).astype(np.int64)
                    x[:, at] += _load(folder, name, panel + 1).reshape(width, -1)
                else:
                    for k in range(width):
                        x[k] += _load(folder, name, k)[lo:hi]
            if not given:
                x /= sum(_load(folder, f"degrees-{g}", 0)[lo:hi] for g in range(groups))
            return x

        return read

    def after(self, vecs: DataFrame, hops: int, label: str = "panel") -> DataFrame:
        """(id, vec) after `hops` averages, also kept as `label`."""
        groups, ranges, n = self.groups, self.ranges, len(self.ids)
        share, folder = -(-n // ranges), self.folder
        fs, base = _open(folder)
        pieces = self._store_vectors(vecs)
        for panel in range(self.panels):
            names, given = pieces, True
            for t in range(hops):
                new = self._hop(names, panel, given, f"hop-{label}-{panel}-{t}")
                self._forget(fs, base, [] if given else names)
                names, given = new, False
            read, parts = self._reader(panel), groups

            def settle(g, read=read, names=names, given=given, panel=panel, parts=parts):
                step = -(-ranges // parts)
                lo, hi = min(n, g * step * share), min(n, (g + 1) * step * share)
                if given:
                    x = read(names, True)[:, lo:hi]
                else:
                    x = read(names, False, lo, hi)
                _save(folder, f"{label}-{panel}-{g}", [x[:, s:min(s + share, hi - lo)] for s in range(0, step * share, share)])

            self._job(parts, settle)
            self._forget(fs, base, [] if given else names)
        self._forget(fs, base, pieces)
        return self.table(label)

    def table(self, *labels: str, weigh: bool = False) -> DataFrame:
        """(id, vec) of what is kept as `labels`, side by side; with `weigh` each row times the root of its node's degree."""
        folder, groups, held, width, n, panels, ranges = self.folder, self.groups, self.held, self.width, len(self.ids), self.panels, self.ranges
        share, step = -(-n // ranges), -(-ranges // groups)

        def rows(batches):
            for b in batches:
                for r in b.column(0).to_pylist():
                    lo, hi = min(n, r * share), min(n, (r + 1) * share)
                    if lo < hi:
                        x = [np.vstack([_load(folder, f"{label}-{p}-{r // step}", r % step).reshape(-1, hi - lo) for p in range(panels)]).T for label in labels]
                        there = np.logical_and.reduce([y[:, width] > 0 for y in x])
                        out = np.hstack([y[there, :width] for y in x])
                        if weigh:
                            out *= np.sqrt(sum(_load(folder, f"degrees-{g}", 0)[lo:hi] for g in range(groups)))[there, None]
                        yield vec_batch(pa.array(held.value[lo:hi][there]), out)

        return self.spark.range(0, ranges, 1, min(ranges, 4 * groups)).mapInArrow(rows, VEC)

    def degrees(self) -> DataFrame:
        """(id, vec): a single number, the root of the node's degree."""
        folder, groups, held, n, ranges = self.folder, self.groups, self.held, len(self.ids), self.ranges
        share = -(-n // ranges)

        def rows(batches):
            for b in batches:
                for r in b.column(0).to_pylist():
                    lo, hi = min(n, r * share), min(n, (r + 1) * share)
                    if lo < hi:
                        yield vec_batch(pa.array(held.value[lo:hi]), np.sqrt(sum(_load(folder, f"degrees-{g}", 0)[lo:hi] for g in range(groups)))[:, None])

        return self.spark.range(0, ranges, 1, min(ranges, 4 * groups)).mapInArrow(rows, VEC)

    def forget(self, label: str) -> None:
        fs, base = _open(self.folder)
        self._forget(fs, base, [f"{label}-{p}-{g}" for p in range(self.panels) for g in range(self.groups)])

    def forget_all(self) -> None:
        fs, base = _open(self.folder)
        fs.delete_dir(base)

    @staticmethod
    def _forget(fs, base: str, names: list[str]) -> None:
        for name in names:
            fs.delete_file(f"{base}/{name}")
