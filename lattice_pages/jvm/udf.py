"""Brings the Java kernels to a session: compiled by Spark's own Janino, sent to the executors as a jar."""

from __future__ import annotations

import os
import tempfile
import zipfile

import numpy as np
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from lattice_pages.jvm.kernels import SOURCE
from lattice_pages.plans.profiles import Profile

NAME = "lattice_page"
_JARS: dict[str, object] = {}
#: Bits of the profile flags, as ``Pages`` names them.
_FLAGS = {"use_predictors": 1, "use_split": 2, "use_rice": 4, "use_gcd": 8, "use_affine": 16, "upper": 32, "persist": 64, "predict": 128, "learn_width": 256}
_VERIFY = 512
#: Bytes before the frame: encode ns, decode ns, mismatches, bits of seven parts, length of the metadata.
HEAD = 88


def covers(p: Profile) -> bool:
    """Whether the Java kernels have the profile: the exact ones on doubles."""
    return p.contract == "exact"


def spec(p: Profile, verify: bool = False) -> Column:
    """The profile as the Java kernels read it. ``verify``: pages are decoded and compared as well."""
    if not covers(p):
        raise ValueError(f"the Java kernels have no profile {p.name}")
    flags = sum(bit for name, bit in _FLAGS.items() if getattr(p, name)) | _VERIFY * verify
    return F.lit(f"{p.block},{p.max_lanes},{flags},{p.alpha!r}")


def _ready(spark: SparkSession) -> None:
    """Compile and send the class once per application, and register it with the session."""
    app, jvm = spark.sparkContext.applicationId, spark.sparkContext._jvm
    if app not in _JARS:
        compiler = jvm.org.codehaus.janino.SimpleCompiler()
        compiler.setParentClassLoader(jvm.org.apache.spark.util.Utils.getContextOrSparkClassLoader())
        compiler.cook(SOURCE)
        path = os.path.join(tempfile.mkdtemp(prefix="ship"), "lattice_pages.jar")
        with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
            for entry in compiler.getBytecodes().entrySet():
                z.writestr(entry.getKey().replace(".", "/") + ".class", bytes(entry.getValue()))
        spark.sparkContext._jsc.addJar(path)
        _JARS[app] = compiler.getClassLoader().loadClass("latticepages.Pages").getDeclaredConstructor(None).newInstance(None)
    spark._jsparkSession.udf().register(NAME, _JARS[app], jvm.org.apache.spark.sql.types.DataTypes.BinaryType)


def coded(spark: SparkSession, words: str, profile: Column) -> Column:
    """The coded pages of the words in a binary column, under profiles from ``spec``; ``unpack`` reads them."""
    _ready(spark)
    return F.call_udf(NAME, F.col(words), profile)


def unpack(data: bytes) -> tuple[bytes, bytes, np.ndarray, float, float, int]:
    """(metadata, payload, bits by part, seconds to encode and to decode, mismatches: -1 if not verified)."""
    head = np.frombuffer(data, ">i8", HEAD // 8)
    meta = HEAD + int(head[10])
    return data[HEAD:meta], data[meta:], head[3:10], head[0] / 1e9, head[1] / 1e9, int(head[2])
