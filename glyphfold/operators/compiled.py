"""Walks that go step by step, in the driver's JVM: their classes are compiled by the compiler that Spark has for its plans."""

from __future__ import annotations

import pkgutil
from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession

#: Values sent to the JVM or back at once.
SENT = 1 << 20


#: Compiled constructors by JVM and name: two classes of one name would be mixed up by the gateway.
MADE: dict[tuple, object] = {}


def java_object(spark: SparkSession, name: str, *args):
    """A new object of the class in ``java/<name>.java``."""
    gateway, jvm = spark.sparkContext._gateway, spark.sparkContext._jvm
    if (gateway, name) not in MADE:
        compiler = jvm.org.codehaus.janino.SimpleCompiler()
        compiler.cook(pkgutil.get_data(__package__, f"java/{name}.java").decode())
        MADE[gateway, name] = compiler.getClassLoader().loadClass(name).getConstructors()[0]
    given = gateway.new_array(jvm.java.lang.Object, len(args))
    for i, x in enumerate(args):
        given[i] = x
    return MADE[gateway, name].newInstance(given)


def packed(x: np.ndarray) -> bytearray:
    return bytearray(np.ascontiguousarray(x, "<i4").tobytes())


def unpacked(x) -> np.ndarray:
    return np.frombuffer(x, "<i4").astype(np.int64)


def chunks(*columns: np.ndarray) -> Iterator[bytearray]:
    """Rows of equally long columns, one after the other, a bounded number at once."""
    for at in range(0, len(columns[0]), SENT):
        yield packed(np.stack([c[at : at + SENT] for c in columns], axis=1))
