"""Java of this package, for loops over one graph that would take Python days: compiled in the driver by the compiler that Spark ships for its own
generated code, and sent to the executors as a jar, once per Spark context. Neither a JDK nor a build step is needed."""

from __future__ import annotations

import tempfile
import threading
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

SOURCES = ("Graph", "Side", "Churn", "Asking", "Shard")
_once = threading.Lock()


def _classes(spark: SparkSession):
    """The class loader that has the compiled classes."""
    with _once:
        return _compiled(spark)


def _compiled(spark: SparkSession):
    sc = spark.sparkContext
    if not getattr(sc, "_navgraph_classes", None):
        jvm, folder = sc._jvm, Path(__file__).resolve().parent
        lanes = jvm.java.lang.ModuleLayer.boot().findModule("jdk.incubator.vector").isPresent()  # Spark asks for it where Java has it
        texts = [(folder / f"{name}.java").read_text() for name in (*SOURCES, "Near" if lanes else "NearPlain")]
        # One unit: one package, all imports first.
        imports = sorted({line for text in texts for line in text.splitlines() if line.startswith("import ")})
        body = [line for text in texts for line in text.splitlines() if not line.startswith(("import ", "package "))]
        compiler = jvm.org.codehaus.janino.SimpleCompiler()
        compiler.setParentClassLoader(jvm.java.lang.Thread.currentThread().getContextClassLoader())
        compiler.cook("\n".join(["package navgraph;", *imports, *body]))
        code = compiler.getBytecodes()
        jar = Path(tempfile.mkdtemp(prefix="navgraph-")) / "navgraph-jvm.jar"
        with zipfile.ZipFile(jar, "w", zipfile.ZIP_DEFLATED) as z:
            for name in code:
                z.writestr(name.replace(".", "/") + ".class", bytes(code[name]))
        sc._jsc.addJar(str(jar))
        sc._navgraph_classes = compiler.getClassLoader()
    return sc._navgraph_classes


def array(spark: SparkSession, kind, values):
    """A Java array; kind: one of int, bool, float (a double), str."""
    sc = spark.sparkContext
    lang, primitive = sc._jvm.java.lang, {int: sc._gateway.jvm.int, bool: sc._gateway.jvm.boolean, float: sc._gateway.jvm.double}
    out = sc._gateway.new_array(lang.String if kind is str else primitive[kind], len(values))
    for i, v in enumerate(values):
        out[i] = kind(v)
    return out


def long(spark: SparkSession, value: int):
    return spark.sparkContext._jvm.java.lang.Long.valueOf(str(value))


def each_partition(df: DataFrame, name: str, arguments: list, ddl: str) -> DataFrame:
    """What an object of class `name`, made with the arguments, gives for every partition of df."""
    spark = df.sparkSession
    sc, loader = spark.sparkContext, _classes(spark)
    given = sc._gateway.new_array(sc._jvm.java.lang.Object, len(arguments))
    for i, v in enumerate(arguments):
        given[i] = v
    step = loader.loadClass(f"navgraph.{name}").getConstructors()[0].newInstance(given)
    schema = spark.createDataFrame([], ddl)._jdf.schema()
    return DataFrame(df._jdf.mapPartitions(step, sc._jvm.org.apache.spark.sql.Encoders.row(schema)), spark)
