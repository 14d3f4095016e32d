"""The kernels' loops in the JVM (Loops.java), with the results of kernels.py.

Spark's own compiler (Janino, of its generated code) makes a class of the source, which the session gives to its executors as a jar. A graph goes there
as one binary value, made by the Python task that would have run the kernel. Where this can't be had, the Python loops run.
"""

from __future__ import annotations

import atexit
import os
import pickle
import shutil
import struct
import tempfile
import threading
import warnings
import zipfile
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

NAME = "modspark_loops"
#: Scores are differences of two products of at most 2m each, which 64 bits hold below this.
MAX_2M = 1 << 31
PASS, RESTREAM, LOUVAIN, EVOLVE = range(4)
_ready: dict[tuple, bool] = {}
_lock = threading.Lock()


def _register(spark: SparkSession) -> None:
    jvm = spark._jvm
    with open(os.path.join(os.path.dirname(os.path.abspath(__file__)), "Loops.java")) as f:
        source = f.read()
    compiler = jvm.org.codehaus.janino.SimpleCompiler()
    compiler.setParentClassLoader(jvm.Thread.currentThread().getContextClassLoader())
    compiler.cook(source)
    made = compiler.getBytecodes()
    folder = tempfile.mkdtemp(prefix="modspark-jar-")  # executors fetch it when their first task comes
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    jar = os.path.realpath(f"{folder}/modspark-loops.jar")
    with zipfile.ZipFile(jar, "w") as z:
        for name in made:
            z.writestr(name.replace(".", "/") + ".class", bytes(made[name]))
    spark.sql(f"ADD JAR '{jar}'")
    found = jvm.Thread.currentThread().getContextClassLoader().loadClass("modspark.Loops")
    one = found.getDeclaredConstructors()[0].newInstance(spark.sparkContext._gateway.new_array(jvm.java.lang.Object, 0))
    spark._jsparkSession.udf().register(NAME, one, spark._jsparkSession.parseDataType('"binary"'))


def ready(spark: SparkSession, two_m: int) -> bool:
    """Whether the loops can run on a graph of this weight."""
    if two_m >= MAX_2M:
        return False
    try:
        key = spark.sparkContext.applicationId, spark._jsparkSession.sessionUUID()
    except Exception:  # no JVM within reach (Spark Connect)
        return False
    with _lock:
        if key not in _ready:
            try:
                _register(spark)
                _ready[key] = True
            except Exception as e:
                _ready[key] = False
                warnings.warn(f"the loops run in Python, since the JVM has not taken them: {e}", stacklevel=2)
    return _ready[key]


def bits(x: float) -> int:
    return struct.unpack("<q", struct.pack("<d", x))[0]


def request(what: int, params: list[int], n: int, src, dst, w, weight, *ints) -> bytes:
    """What Loops.call() reads: a graph of arcs sorted by their ends, as places. Parallel arcs merge, loops stay apart."""
    out = src != dst
    loop = np.zeros(n, np.int64)
    np.add.at(loop, src[~out], w[~out])
    src, dst, w = src[out], dst[out], np.asarray(w[out], np.int64)
    if len(src):
        first = np.flatnonzero(np.r_[True, (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])])
        src, dst, w = src[first], dst[first], np.add.reduceat(w, first)
    head = [what, n, len(src), len(params), sum(map(len, ints)), *params]
    longs = [np.asarray(x, "<i8").tobytes() for x in (head, w, loop, weight)]
    return b"".join([*longs, *(np.asarray(x, "<i4").tobytes() for x in (np.searchsorted(src, np.arange(n + 1)), dst, *ints))])


def names(label) -> tuple[np.ndarray, np.ndarray]:
    """The labels' names in order, and each node's place among them: ties between places are those between names."""
    return np.unique(np.asarray(label, np.int64), return_inverse=True)


def run(spark: SparkSession, grouped, pack: Callable, unpack: Callable, schema: str) -> DataFrame:
    """pack(pdf) -> (tag, request) of each group; unpack(tag, told, labels) -> a frame of schema. told: the answer's whole numbers."""

    def make(pdf: pd.DataFrame) -> pd.DataFrame:
        tag, asked = pack(pdf)
        return pd.DataFrame({"tag": [pickle.dumps(tag)], "request": [asked]})

    def read(frames):
        for frame in frames:
            for tag, answer in zip(frame["tag"], frame["answer"], strict=True):
                size = 8 + 8 * int(np.frombuffer(answer, "<i8", 1)[0])
                yield unpack(pickle.loads(tag), np.frombuffer(answer[8:size], "<i8"), np.frombuffer(answer, "<i4", offset=size))

    packed = grouped.applyInPandas(make, "tag binary, request binary")
    return packed.select("tag", F.call_function(NAME, "request").alias("answer")).mapInPandas(read, schema)
