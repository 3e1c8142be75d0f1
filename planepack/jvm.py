"""The byte loops of :mod:`foundational` inside the JVM: ``Kernels.java``, compiled by the compiler that Spark brings for its own code.

The classes go to the executors as a jar of the session, so that blocks are encoded where they lie and do not pass through Python.  Sizes, streams and
decoded blocks are those of the Python forms, which run where a session gives no access to its JVM.
"""

from __future__ import annotations

import hashlib
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, DataType, LongType

#: Codecs of the registry that have a form there.
NAMES = {"lz77", "fastlz", "huffman", "xor", "xor-of-128", "delta", "hashed", "stride-lz"}
_FUNCTIONS: dict[str, tuple[str, DataType]] = {"pp_jvm_measure": ("planepack.Measure", ArrayType(ArrayType(LongType()))), "pp_jvm_code": ("planepack.Code", BinaryType())}
_held = tempfile.TemporaryDirectory(prefix="planepack-jar-", ignore_cleanup_errors=True)


def _jar(spark: SparkSession) -> str:
    source = (Path(__file__).parent / "Kernels.java").read_text()
    path = Path(_held.name) / f"kernels-{hashlib.sha256(source.encode()).hexdigest()[:16]}.jar"
    if not path.exists():
        jvm = spark._jvm
        compiler = jvm.org.codehaus.janino.SimpleCompiler()
        compiler.setParentClassLoader(jvm.org.apache.spark.util.Utils.getContextOrSparkClassLoader())
        compiler.cook(source)
        made = compiler.getBytecodes()
        with zipfile.ZipFile(path, "w") as z:
            for name in made.keySet():
                z.writestr(f"{name.replace('.', '/')}.class", bytes(made.get(name)))
    return str(path)


def register(spark: SparkSession) -> bool:
    """Make the functions callable by name; false where there is no JVM to reach."""
    if getattr(spark, "_jsparkSession", None) is None:
        return False
    if not spark._jsparkSession.catalog().functionExists("pp_jvm_measure"):
        spark.sql(f"add jar '{_jar(spark)}'")
        for name, (cls, kind) in _FUNCTIONS.items():
            f = spark._jvm.org.apache.spark.util.Utils.classForName(cls, True, False).newInstance()
            spark._jsparkSession.udf().register(name, f, spark._jsparkSession.parseDataType(kind.json()))
    return True


def fits(spec) -> bool:
    """Whether the JVM has all of a plan: its codec, without a choice per block."""
    return spec.codec in NAMES and spec.mode in ("user", "standard") and spec.scope != "block" and not spec.guard and spec.cluster_order == "plane"


def job_line(codec: str, packing: str, layout: str, partition, decode: bool) -> str:
    return ";".join((codec, packing, layout, str(int(decode)), "/".join(",".join(map(str, g)) for g in partition)))


def measure(blocks: DataFrame, lines: dict[str, list[str]]) -> DataFrame:
    """(dataset, raw, at, m): a row per block and job.  ``lines``: by dataset a line a job, empty for a job that does not apply."""
    named = F.create_map(*(F.lit(x) for ds, each in lines.items() for x in (ds, "\n".join(each))))
    jobs = F.element_at(named, F.col("dataset"))
    t = blocks.select("dataset", F.length("data").cast("long").alias("raw"), F.posexplode(F.call_function("pp_jvm_measure", "data", "width", jobs)).alias("at", "m"))
    return t.filter("m is not null")
