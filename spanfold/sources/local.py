"""Key ranges of clustered files without a scan: read by the driver up to a stated number of points, and
piece by piece by tasks that go through points in key order."""

from __future__ import annotations

from collections import OrderedDict

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import pyarrow.parquet as pq

MOST_POINTS = 1 << 16  # of all scans of a request; more are read by a Spark job
OPEN_FILES = 256


class LocalReader:
    """Columns of key ranges from the bucket folders of a clustered source.

    Folders are listed when first asked for and footers kept for the files used last, so memory
    does not grow with the source; row groups are chosen by their key statistics.
    """

    def __init__(self, path: str, key: str, bucket_width: int):
        self.store, self.root = pafs.FileSystem.from_uri(path)
        self.path, self.key, self.width = path, key, bucket_width
        self.files: OrderedDict[int, list] = OrderedDict()

    def _bucket(self, bucket: int) -> list:
        if bucket not in self.files:
            found = self.store.get_file_info(pafs.FileSelector(f"{self.root}/bucket={bucket}", allow_not_found=True))
            names = sorted(f.path for f in found if f.is_file and f.path.endswith(".parquet"))
            self.files[bucket] = [pq.ParquetFile(self.store.open_input_file(n)) for n in names]
            while sum(map(len, self.files.values())) > OPEN_FILES and len(self.files) > 1:
                self.files.popitem(last=False)
        self.files.move_to_end(bucket)
        return self.files[bucket]

    def _groups(self, file: pq.ParquetFile, lo: int, hi: int) -> list[int]:
        at = file.schema_arrow.get_field_index(self.key)
        out = []
        for g in range(file.metadata.num_row_groups):
            s = file.metadata.row_group(g).column(at).statistics
            if s is None or not s.has_min_max or (s.min < hi and s.max >= lo):
                out.append(g)
        return out

    def read(self, lo: int, hi: int) -> pa.Table:
        """All columns of the points of [lo, hi) in key order."""
        parts = []
        for bucket in range(lo // self.width, (hi - 1) // self.width + 1):
            for file in self._bucket(bucket):
                if groups := self._groups(file, lo, hi):
                    t = file.read_row_groups(groups, use_threads=False)
                    k = t.column(self.key).to_numpy()
                    inside = np.flatnonzero((k >= lo) & (k < hi))
                    if len(inside):
                        whole = inside[-1] - inside[0] + 1 == len(inside)
                        parts.append(t.slice(inside[0], len(inside)) if whole else t.take(pa.array(inside)))
        if not parts:
            return pa.table({})
        out = pa.concat_tables(parts)
        k = out.column(self.key).to_numpy()
        return out if (k[1:] >= k[:-1]).all() else out.take(pa.array(np.argsort(k, kind="stable")))


def exact_gram(x: np.ndarray) -> list[list[int]]:
    """Second moments of integer columns, exact: columns are cut into limbs so short that sums of
    their products stay whole numbers of 53 bits, which floating-point products keep exactly."""
    n, d = x.shape
    bits = (53 - max(1, n).bit_length()) // 2 - 1
    limbs, place = [], []
    for j in range(d):
        col, shift = x[:, j], 0
        while True:
            top = not len(col) or int(np.abs(col).max()) < 1 << bits
            limbs.append((col if top else col & ((1 << bits) - 1)).astype(np.float64))
            place.append((j, shift))
            if top:
                break
            col, shift = col >> bits, shift + bits
    m = np.stack(limbs, axis=1)
    g = m.T @ m
    out = [[0] * d for _ in range(d)]
    for a, (i, s) in enumerate(place):
        for b, (j, t) in enumerate(place):
            out[i][j] += int(g[a, b]) << (s + t)
    return out
