"""What a Spark session needs before functions of this package can run on executors."""

from __future__ import annotations

import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_NAME = "keysieve_package.zip"
#: Bytes of an Arrow batch: a task holds a batch in the executor's JVM and in its Python worker, some of them twice.
_BATCH, _BYTES = "spark.sql.execution.arrow.maxBytesPerBatch", 4 << 20


def ship(spark: SparkSession) -> SparkSession:
    """Sends this package's modules to the executors once, and bounds the session's Arrow batches by their bytes.

    A session on the same context finds the modules there; a smaller bound of its own stays.
    """
    sc = spark.sparkContext
    if not 0 < sc._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get(_BATCH)) <= _BYTES:
        spark.conf.set(_BATCH, str(_BYTES))
    if _NAME not in sc._python_includes:
        root = Path(__file__).resolve().parent
        path = Path(tempfile.mkdtemp(prefix="keysieve-")) / _NAME
        with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
            for file in sorted(root.rglob("*.py")):
                z.write(file, file.relative_to(root.parent))
            if (pipeline := root.parent / "corpus_pipeline.py").exists():
                z.write(pipeline, pipeline.name)
        sc.addPyFile(str(path))
    return spark
