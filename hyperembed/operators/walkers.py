"""Steps of many walks at once, for large graphs: memberships are sorted into files once, by node and by hyperedge, and only the walks'
places move between tasks. A task holds the file of one share of the nodes or hyperedges at a time.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions.vectors import mix_numbers
from ..session import work_folder
from .panels import _open

#: Memberships up to which joins do; memberships of a file.
JOINED, FILE_ROWS = 2_000_000, 500_000
LONGS = pa.schema([("x", pa.int64())])
PLACE = "start long, walk int, vid long, eid long, inside boolean"


def _share(column: str, files: int):
    return F.pmod(F.xxhash64(column), F.lit(files)).cast("int").alias("share")


def _picker(folder: str, key: str):
    """pick(share, at, number): of the list of each key in `at` the entry `number` modulo its length."""
    held = {}

    def load(i):
        if i not in held:
            held.clear()
            fs, base = _open(folder)
            with fs.open_input_file(f"{base}/{key}-{i}") as f, pa.ipc.open_file(f) as r:
                held[i] = [r.get_batch(k).column(0).to_numpy() for k in range(3)]
        return held[i]

    def pick(share, at, number):
        out = np.zeros(len(at), np.int64)
        for i in np.unique(share).tolist():
            some = np.flatnonzero(share == i)
            ids, first, lists = load(i)
            k = np.searchsorted(ids, at[some])
            if (ids[np.minimum(k, len(ids) - 1)] != at[some]).any():
                raise RuntimeError(f"a walk is at a {key} that has no memberships")
            out[some] = lists[first[k] + number[some] % (first[k + 1] - first[k])]
        return out

    return pick


class Walkers:
    """Memberships (eid, vid) in files; `step` is that of `baselines.walk_corpus`."""

    def __init__(self, inc: DataFrame, size: int, p: float, seed: int, restart: float | None):
        spark = inc.sparkSession
        self.p, self.seed, self.restart = p, seed, restart
        self.files = max(spark.sparkContext.defaultParallelism, -(-size // FILE_ROWS))
        self.folder = f"{work_folder(spark)}/graph-walkers-{uuid.uuid4().hex}"
        if "://" not in self.folder and not self.folder.startswith("file:"):
            self.folder = f"file://{self.folder}"
        fs, base = _open(self.folder)
        fs.create_dir(base, recursive=True)
        for key, other in (("vid", "eid"), ("eid", "vid")):
            self._store(inc, key, other)

    def _store(self, inc: DataFrame, key: str, other: str) -> None:
        """A file for each share of the keys: keys in order, where their lists start, the lists in order."""
        folder = self.folder

        def run(batches):
            parts = [[np.array(b.column(c).to_numpy()) for c in range(3)] for b in batches if b.num_rows]
            if not parts:
                return
            share, own, to = (np.concatenate(x) for x in zip(*parts))
            del parts
            fs, base = _open(folder)
            for i in np.unique(share).tolist():
                some = np.flatnonzero(share == i)
                some = some[np.lexsort((to[some], own[some]))]
                ids, first = np.unique(own[some], return_index=True)
                with fs.open_output_stream(f"{base}/{key}-{i}", compression=None) as out, pa.ipc.new_file(out, LONGS) as w:
                    for x in (ids, np.r_[first, len(some)], to[some]):
                        w.write_batch(pa.RecordBatch.from_arrays([pa.array(x.astype(np.int64))], schema=LONGS))
                yield pa.RecordBatch.from_pydict({"share": [int(i)]})

        inc.select(_share(key, self.files), key, other).repartition(self.files, "share").mapInArrow(run, "share long").collect()

    def step(self, at: DataFrame, t: int) -> DataFrame:
        """Places (start, walk, vid, eid, inside) after step `t`; `inside` tells that the walk may stay in its hyperedge."""
        folder, p, seed, restart, files = self.folder, self.p, self.seed, self.restart, self.files
        names = ["start", "walk", "vid", "eid", "inside"]

        def numbers(batch):
            share, start, walk, vid, eid, inside = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("share", *names))
            return share, start, walk, vid, eid, inside, lambda s: mix_numbers(start * 131 + walk, t * 7 + s, seed)

        def chance(number):
            return number % 1_000_000 / 1_000_000

        def from_nodes(batches):
            pick = _picker(folder, "vid")
            for b in batches:
                share, start, walk, vid, eid, inside, number = numbers(b)
                go = ~(inside & (chance(number(1)) < p))
                eid = eid.copy()
                eid[go] = pick(share[go], vid[go], number(2)[go])
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (start, walk, vid, eid, inside)], names)

        def from_edges(batches):
            pick = _picker(folder, "eid")
            for b in batches:
                share, start, walk, vid, eid, inside, number = numbers(b)
                vid = pick(share, eid, number(3))
                back = chance(number(4)) < restart if restart is not None else np.zeros(len(vid), bool)
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (start, walk, np.where(back, start, vid), eid, ~back)], names)

        mid = at.select(_share("vid", files), *names).repartition(files, "share").mapInArrow(from_nodes, PLACE)
        return mid.select(_share("eid", files), *names).repartition(files, "share").mapInArrow(from_edges, PLACE)
