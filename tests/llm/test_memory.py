"""Stages of the pipeline share their executors, and so what these hold."""

import gc
import inspect

import corpus_pipeline
from tmotif.llm.common import executors_give_back


def test_executors_collect_garbage(spark):
    jvm = spark.sparkContext._jvm
    ref = jvm.java.lang.ref.WeakReference(jvm.java.util.ArrayList())
    gc.collect()  # what Python held of the list goes
    assert executors_give_back(spark) == spark.sparkContext.defaultParallelism
    assert ref.get() is None


def test_every_stage_gives_back():
    for _, stage in corpus_pipeline.STAGES:
        assert "executors_give_back(spark)" in inspect.getsource(stage)
