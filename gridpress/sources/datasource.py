"""spark.read.format("gridarchive"): decompression as a scan, with slices and strides on factor rows first."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual


class Rows(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class ArchiveReader(DataSourceReader):
    """Restores row blocks of the first axis; predicates on axes become factor rows before any product."""

    def __init__(self, core: np.ndarray, factors: list[np.ndarray], axes: list[str]):
        self.core, self.factors, self.axes = core, factors, axes
        self.rows = [np.arange(len(u)) for u in factors]

    def pushFilters(self, filters: list[Filter]):  # noqa: N802
        for f in filters:
            name = f.attribute[0] if getattr(f, "attribute", None) else None
            if name in self.axes and isinstance(f, (EqualTo, GreaterThan, GreaterThanOrEqual, LessThan, LessThanOrEqual)):
                n = self.axes.index(name)
                r, v = self.rows[n], f.value
                ok = {EqualTo: r == v, GreaterThan: r > v, GreaterThanOrEqual: r >= v, LessThan: r < v, LessThanOrEqual: r <= v}[type(f)]
                self.rows[n] = r[ok]
            else:
                yield f

    def partitions(self):
        n = len(self.rows[0])
        step = max(1, -(-n // 8))
        return [Rows(i, min(n, i + step)) for i in range(0, n, step)] or [Rows(0, 0)]

    def read(self, partition):
        from gridpress.operators.transform import inverse_array

        rows = [self.rows[0][partition.lo : partition.hi], *self.rows[1:]]
        if any(not len(r) for r in rows):
            return
        v = inverse_array(self.core, [u[r] for u, r in zip(self.factors, rows, strict=True)], skip_zero_slices=True)
        grid = np.meshgrid(*rows, indexing="ij")
        yield pa.RecordBatch.from_arrays([*(pa.array(g.ravel().astype(np.int32)) for g in grid), pa.array(v.ravel())], names=[*self.axes, "v"])


class ArchiveSource(DataSource):
    """Options: axes, and what read_archive hands over."""

    @classmethod
    def name(cls) -> str:
        return "gridarchive"

    def schema(self) -> str:
        return ", ".join(f"{a} int" for a in self.options["axes"].split(",")) + ", v double"

    def reader(self, schema):
        import base64
        import io

        data = np.load(io.BytesIO(base64.b64decode(self.options["held"])), allow_pickle=False)
        return ArchiveReader(data["core"], [data[f"f{i}"] for i in range(int(data["n"]))], self.options["axes"].split(","))


def read_archive(spark: SparkSession, path: str, **options):
    """DataFrame of an archive of at most LOCAL_CELLS coefficients through the data source.

    A data source plans in a process of its own without a session, so core and
    factors are read here and handed over as options.
    """
    import base64
    import io

    from gridpress.operators.codec import core_array, open_archive
    from gridpress.operators.resample import decimate
    from gridpress.session import ship

    ship(spark)
    a = open_archive(path, spark)
    if "decimate" in options:
        a = decimate(a, int(options["decimate"]), options.get("how", "lanczos2"))
    held = io.BytesIO()
    np.savez_compressed(held, core=core_array(a, options.get("uptoPlane")), n=len(a.coded), **{f"f{i}": u for i, u in enumerate(a.factors())})
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(ArchiveSource)
    return spark.read.format("gridarchive").option("axes", ",".join(a.header["axes"])).option("held", base64.b64encode(held.getvalue()).decode()).load()
