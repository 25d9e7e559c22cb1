"""The plain kernels as Spark functions that run in the executors' own process, without Python workers."""

from __future__ import annotations

import atexit
import pkgutil
import shutil
import tempfile
import zipfile

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

#: Characters of a string up to which these functions take it: they hold 32 bytes a character, in the heap.
JVM_CHARS = 8 << 20
#: Characters up to which ``work`` takes a string: 12 bytes a character in the heap, 4 outside it, and the string itself.
LEAN_CHARS = 96 << 20
#: Characters up to which all phrases of a string may be one row.
ROW_CHARS = 1 << 20
METHODS = ("two_way", "lz77", "lz_next", "lz_backward", "lex")
#: Methods of the kernels that take little memory.
LEAN_METHODS = ("two_way", "lz77", "lz_next", "lex")
FUNCTIONS = {
    "phrasework_counts": ("Counts", "array<struct<method: string, direction: string, n: bigint, phrases: bigint, literals: bigint, copies: bigint, left_refs: bigint, right_refs: bigint, seconds: double>>"),
    "phrasework_costs": ("Costs", "array<struct<method: string, direction: string, n: bigint, phrases: bigint, literals: bigint, copies: bigint, left_refs: bigint, right_refs: bigint, seconds: double, bytes: bigint>>"),
    "phrasework_work": ("Work", "array<struct<method: string, direction: string, n: bigint, phrases: bigint, unions: bigint, candidates: bigint, most_candidates: bigint, finds: bigint, work_bound: bigint>>"),
    "phrasework_parse": ("Parse", "array<struct<start: bigint, length: bigint, ref: bigint, literal: string, side: string>>"),
    "phrasework_decode": ("Decode", "string"),
}

_compiled: dict[str, tuple] = {}


def prepare(spark: SparkSession) -> None:
    """Compile the kernels with the compiler Spark itself uses, give them to the executors, name the functions."""
    context = spark.sparkContext
    jvm, gateway = context._jvm, context._gateway
    if context.applicationId not in _compiled:
        compiler = jvm.org.codehaus.janino.SimpleCompiler()
        compiler.setTargetVersion(8)
        compiler.cook(pkgutil.get_data("phrasework.kernels", "Kernels.java").decode())
        folder = tempfile.mkdtemp(prefix="phrasework-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        classes = compiler.getBytecodes()
        with zipfile.ZipFile(f"{folder}/phrasework-kernels.jar", "w") as jar:
            for name in classes.keySet():
                jar.writestr(name.replace(".", "/") + ".class", bytes(classes[name]))
        context._jsc.addJar(f"{folder}/phrasework-kernels.jar")
        _compiled[context.applicationId] = compiler.getClassLoader(), set()
    loader, sessions = _compiled[context.applicationId]
    session = spark._jsparkSession.sessionUUID()
    if session not in sessions:
        for name, (kind, schema) in FUNCTIONS.items():
            made = loader.loadClass(f"phrasework.Kernels${kind}").getDeclaredConstructor(gateway.new_array(jvm.java.lang.Class, 0)).newInstance(gateway.new_array(jvm.java.lang.Object, 0))
            spark._jsparkSession.udf().register(name, made, jvm.org.apache.spark.sql.types.DataType.fromDDL(schema))
        sessions.add(session)


def counts(spark: SparkSession, text: str, methods: tuple[str, ...], directions: tuple[str, ...]) -> Column:
    prepare(spark)
    return F.call_function("phrasework_counts", F.col(text), F.lit(",".join(methods)), F.lit(",".join(directions)))


def costs(spark: SparkSession, text: str, methods: tuple[str, ...], directions: tuple[str, ...]) -> Column:
    """``counts`` by the kernels that take little memory, whatever the length, with the peak bytes of their arrays."""
    prepare(spark)
    return F.call_function("phrasework_costs", F.col(text), F.lit(",".join(methods)), F.lit(",".join(directions)))


def work(spark: SparkSession, text: str, way: Column, wanted: Column) -> Column:
    """Phrases of each ``wanted`` method:direction from one suffix order, the text's own or (``way``) the reversed text's.

    Left and right parses of either direction come from both orders, the others from their own; the two-way
    parse has its work with it. Strings take little memory and wait for room, so that long ones run one by one.
    """
    prepare(spark)
    return F.call_function("phrasework_work", F.col(text), way, wanted)


def parse(spark: SparkSession, text: str, method: str) -> Column:
    prepare(spark)
    return F.call_function("phrasework_parse", F.col(text), F.lit(method))


def decode(spark: SparkSession, phrases: Column) -> Column:
    """Text of an array of phrases; null where a chain of references ends in no literal."""
    prepare(spark)
    return F.call_function("phrasework_decode", phrases)
