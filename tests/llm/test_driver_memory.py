"""The driver of the pipeline gives back what it has freed: its Python's memory and its JVM's outside the heap."""

import os

import numpy as np
import pytest
from py4j.protocol import Py4JError

from lattice_pages import session


def _resident(pid: int) -> float:
    with open(f"/proc/{pid}/statm") as f:
        return int(f.read().split()[1]) * os.sysconf("SC_PAGE_SIZE") / 2**20


def test_release_gives_back_what_python_has_freed(spark):
    session.release(spark)
    before = _resident(os.getpid())
    held = [np.ones(5_000) for _ in range(4_000)]  # 40 kB each: below what the allocator maps on its own
    pins = held[::100] + held[-1:]  # the allocator keeps all that lies between
    held = None
    kept = _resident(os.getpid()) - before
    session.release(spark)
    assert kept > 100 and _resident(os.getpid()) - before < 0.3 * kept and len(pins) == 41


def test_release_gives_back_what_the_jvm_has_freed(spark):
    if session.trim_jvm(spark) is None:
        pytest.skip("this JVM has no command for it")
    jvm = spark.sparkContext._jvm
    pid = jvm.java.lang.ProcessHandle.current().pid()
    held = [jvm.java.util.zip.Deflater() for _ in range(600)]  # buffers outside the heap
    for i, d in enumerate(held):
        if i % 50 and i < len(held) - 1:
            d.end()
    jvm.System.gc()  # the heap itself is no part of this
    kept = _resident(pid)
    session.release(spark)
    after = _resident(pid)
    for d in held:
        d.end()
    assert kept - after > 30


def test_a_jvm_without_the_command_is_left_as_it_is():
    class Bare:
        def __getattr__(self, name):
            raise Py4JError(name)

    class Context:
        _jvm, _gateway = Bare(), None

    class Session:
        sparkContext = Context()

    assert session.trim_jvm(Session()) is None


@pytest.mark.parametrize("name", ["language", "near_copies", "personal_data", "packing"])
def test_each_stage_begins_with_what_is_free_given_back(spark, sf, monkeypatch, name):
    pipeline = pytest.importorskip("corpus_pipeline")
    done = []
    give, trim = session.give_back, session.trim_jvm
    monkeypatch.setattr(session, "give_back", lambda: (done.append("python"), give())[1])
    monkeypatch.setattr(session, "trim_jvm", lambda s: (done.append("jvm"), trim(s))[1])

    class Begun(Exception):
        pass

    class Docs:  # whatever the stage does first with its rows
        def __getattr__(self, name):
            raise Begun

    with pytest.raises(Begun):
        dict(pipeline.STAGES)[name](spark, Docs(), sf)
    assert done == ["python", "jvm"]
