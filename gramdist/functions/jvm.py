"""Kernels in Java: compiled by the compiler that Spark's own code generation uses, sent to the executors as a jar."""

from __future__ import annotations

import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

from ..session import own

_SENT: dict[str, object] = {}  # the function's object by application


def unit_tile(spark: SparkSession) -> str:
    """Registers UnitTile.java's function of (a, b, top, left, at) and gives its name."""
    sc, jvm = spark.sparkContext, spark._jvm
    if sc.applicationId not in _SENT:
        compiler = jvm.org.codehaus.janino.SimpleCompiler()
        compiler.cook((Path(__file__).parent / "UnitTile.java").read_text())
        folder = Path(tempfile.mkdtemp(prefix="gramdist-"))
        own(str(folder))
        with zipfile.ZipFile(folder / "gramdist-unit-tile.jar", "w") as jar:
            for name, code in compiler.getBytecodes().items():
                jar.writestr(name.replace(".", "/") + ".class", bytes(code))
        sc._jsc.addJar(str(folder / "gramdist-unit-tile.jar"))
        made = compiler.getClassLoader().loadClass("gramdist.UnitTile")
        none = sc._gateway.new_array(jvm.java.lang.Class, 0), sc._gateway.new_array(jvm.java.lang.Object, 0)
        _SENT[sc.applicationId] = made.getDeclaredConstructor(none[0]).newInstance(none[1])
    name = "gramdist_unit_tile"
    spark._jsparkSession.udf().register(name, _SENT[sc.applicationId], jvm.org.apache.spark.sql.types.DataTypes.BinaryType)
    return name
