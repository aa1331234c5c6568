"""Data source of frame files (`hitframes`): batches of hits, with event ranges as options or pushed filters, and streams.

Options: path (a folder of frame files that PyArrow can open), models (as `save_models` writes them), channels, and lo, hi
(events). Large files make several partitions, which share their row groups; a row group is read at a time, and those
outside the range are skipped by their statistics. A stream takes files in order of their time and name; a file counts
once it is `settle` seconds old (option, 0), so that none written at the same time is missed.
"""

from __future__ import annotations

import base64
import pickle
import time
import zlib

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, EqualTo, GreaterThanOrEqual, InputPartition, LessThanOrEqual

HITS = "event long, channel int, rise long, fall long"


def save_models(models: dict) -> str:
    """Models as a text option."""
    return base64.b64encode(zlib.compress(pickle.dumps(models))).decode()


def load_models(text: str) -> dict:
    return pickle.loads(zlib.decompress(base64.b64decode(text)))


PART_BYTES = 128 << 20


class _Part(InputPartition):
    """Each `of`-th row group of a file, from the `index`-th on."""

    def __init__(self, path: str, index: int, of: int):
        super().__init__((path, index, of))


class _Frames:
    """What batches and streams share."""

    def __init__(self, options):
        self.path = options["path"]
        self.models, self.channels = options["models"], int(options["channels"])
        self.lo, self.hi = int(options.get("lo", -(2**62))), int(options.get("hi", 2**62))

    def _system(self):
        from pyarrow import fs

        return fs.FileSystem.from_uri(self.path) if "://" in self.path or self.path.startswith("file:") else (fs.LocalFileSystem(), self.path)

    def _files(self) -> list[tuple[int, str, int]]:
        """Time of change (ns), path and size of the frame files, in this order. Names that begin with _ or . are not finished."""
        from pyarrow import fs

        system, path = self._system()
        found = system.get_file_info(fs.FileSelector(path, recursive=True, allow_not_found=True))
        hidden = lambda p: any(x[:1] in "_." for x in p[len(path) :].split("/") if x)
        return sorted((f.mtime_ns or 0, f.path, f.size) for f in found if f.path.endswith(".parquet") and not hidden(f.path))

    def _parts(self, files):
        of = lambda size: max(1, -(-size // PART_BYTES))
        return [_Part(path, k, of(size)) for _, path, size in files for k in range(of(size))]

    def read(self, partition):
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc
        import pyarrow.parquet as pq

        from hitcodec.operators.frames import NAMES, decode_rows

        path, index, of = partition.value
        models = load_models(self.models)
        with self._system()[0].open_input_file(path) as source:
            file = pq.ParquetFile(source)
            places = {file.schema_arrow.names[k]: k for k in range(len(file.schema_arrow.names))}
            for group in range(index, file.num_row_groups, of):
                about = file.metadata.row_group(group)
                lo, hi = (about.column(places[n]).statistics for n in ("lo_event", "hi_event"))
                if lo is not None and lo.has_min_max and (lo.min > self.hi or hi.max < self.lo):
                    continue
                for batch in file.iter_batches(4096, [group], columns=NAMES):
                    batch = batch.filter(pc.and_(pc.greater_equal(batch["hi_event"], self.lo), pc.less_equal(batch["lo_event"], self.hi)))
                    for e, c, r, f in decode_rows(batch, models, self.channels) if batch.num_rows else ():
                        keep = (e >= self.lo) & (e <= self.hi)
                        yield pa.RecordBatch.from_arrays([pa.array(e[keep]), pa.array(c[keep].astype(np.int32)), pa.array(r[keep]), pa.array(f[keep])], ["event", "channel", "rise", "fall"])


class FrameReader(_Frames, DataSourceReader):
    def pushFilters(self, filters):
        for f in filters:
            name = getattr(f, "attribute", None)
            if name == ("event",) and isinstance(f, GreaterThanOrEqual):
                self.lo = max(self.lo, f.value)
            elif name == ("event",) and isinstance(f, LessThanOrEqual):
                self.hi = min(self.hi, f.value)
            elif name == ("event",) and isinstance(f, EqualTo):
                self.lo, self.hi = max(self.lo, f.value), min(self.hi, f.value)
            yield f  # rows are filtered by Spark as well

    def partitions(self):
        return self._parts(self._files())


class FrameStreamReader(_Frames, DataSourceStreamReader):
    def __init__(self, options):
        super().__init__(options)
        self.settle = float(options.get("settle", 0))

    def initialOffset(self) -> dict:
        return {"time": -1, "path": ""}

    def latestOffset(self) -> dict:
        old = time.time_ns() - int(self.settle * 1e9)
        done = [f for f in self._files() if f[0] <= old]
        return {"time": done[-1][0], "path": done[-1][1]} if done else self.initialOffset()

    def partitions(self, start: dict, end: dict):
        after, upto = (start["time"], start["path"]), (end["time"], end["path"])
        return self._parts([f for f in self._files() if after < f[:2] <= upto])


class FrameSource(DataSource):
    @classmethod
    def name(cls):
        return "hitframes"

    def schema(self):
        return HITS

    def reader(self, schema):
        return FrameReader(self.options)

    def streamReader(self, schema):
        return FrameStreamReader(self.options)


def register(spark) -> None:
    """Make the source known; Spark hands filters to Python sources only with this setting."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(FrameSource)
