"""Language models behind one interface, with a cache of answers.

Every role of a model (plan, generate, judge, dates, schema, extract) is a request, which is JSON, and
an answer, which is JSON as well (``plans/roles.py`` has the requests and reads the answers).  ``CachedCalls`` looks requests up by digest, asks for each distinct miss once, stores the
answers before anything uses them, and joins them back: a retried task or a second run asks nothing.
"""

from __future__ import annotations

import json
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import written

CACHE = "key string, role string, backend_id string, request string, response string, error string"


@dataclass
class CallableBackend:
    """A model as a function from role and request to an answer.

    Decoding is deterministic at temperature 0; the temperature is part of every request's key, so answers
    of one setting are never taken for those of another.
    """

    backend_id: str
    call: Callable[[str, str], str]
    temperature: float = 0.0
    retries: int = 1
    wait: float = 0.0

    def ask(self, role: str, request: dict) -> dict | list | str:
        """One structured answer on the driver; malformed ones are asked for again with the error."""
        error = ""
        for _ in range(self.retries + 1):
            sent = dict(request, error=error) if error else request
            try:
                return json.loads(self.call(role, json.dumps(sent, sort_keys=True)))
            except ValueError as e:
                error = str(e)
        raise ValueError(f"{role}: {error}")

    def plan(self, request: dict) -> list:
        return self.ask("plan", request)

    def map_batches(self, role: str) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
        """For ``mapInPandas``: requests to answers, one client a partition, retried, never failing the job."""
        call, retries, wait = self.call, self.retries, self.wait

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                answers, errors = [], []
                for request in pdf["request"]:
                    answer, error = None, None
                    for turn in range(retries + 1):
                        try:
                            answer = call(role, request)
                            json.loads(answer)
                            error = None
                            break
                        except Exception as e:  # a model's failure is a row's, not the job's
                            answer, error = None, f"{type(e).__name__}: {e}"
                            time.sleep(wait * 2**turn)
                    answers.append(answer)
                    errors.append(error)
                yield pdf.assign(response=answers, error=errors)

        return run


def cache_key(role, backend_id, temperature, request):
    return F.md5(F.to_json(F.struct(role.alias("role"), backend_id.alias("backend"), temperature.alias("temperature"), request.alias("request"))))


class CachedCalls:
    """Answers for a column of requests: those that the cache has, and one call for each distinct other.

    An answer is kept for good; a failure is kept as a record alone and asked for again by the next run.
    """

    def __init__(self, spark: SparkSession, backend: CallableBackend, path: str, partitions: int | None = None):
        self.spark, self.backend, self.path, self.partitions = spark, backend, path, partitions

    def cache(self) -> DataFrame:
        at = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        if not at.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(at):
            return self.spark.createDataFrame([], CACHE)
        return self.spark.read.schema(CACHE).parquet(self.path)

    def answers(self, df: DataFrame, role: str, request) -> DataFrame:
        """``df`` with ``response``, ``error`` and ``cached``."""
        b = self.backend
        key = cache_key(F.lit(role), F.lit(b.backend_id), F.lit(float(b.temperature)), F.col("__request"))
        keyed = df.withColumn("__request", request).withColumn("__key", key)
        known = written(self.cache().where("error is null").select(F.col("key").alias("__old")).distinct(), "known-answers")
        wanted = keyed.select(F.col("__key").alias("key"), F.col("__request").alias("request"))
        misses = wanted.join(known, F.col("key") == F.col("__old"), "left_anti").dropDuplicates(["key"])
        if self.partitions:
            misses = misses.repartition(self.partitions, "key")
        asked = misses.withColumn("role", F.lit(role)).withColumn("backend_id", F.lit(b.backend_id)).select("key", "role", "backend_id", "request")
        asked.mapInPandas(b.map_batches(role), CACHE).write.mode("append").parquet(self.path)
        # an answer before a failure, and of several answers always the same.  Written, because scans of one path
        # count as equal in a plan whatever files they list: a later call's answers would be taken for these
        stored = self.cache().join(wanted.select("key").distinct(), "key", "left_semi").groupBy("key").agg(F.min(F.struct(F.col("error").isNotNull().alias("failed"), "response", "error")).alias("__a"))
        stored = written(stored, "answers")
        joined = keyed.join(stored, F.col("__key") == F.col("key"), "left").join(known, F.col("__key") == F.col("__old"), "left")
        out = joined.withColumn("response", F.when(~F.col("__a.failed"), F.col("__a.response"))).withColumn("error", F.col("__a.error")).withColumn("cached", F.col("__old").isNotNull())
        return out.drop("__request", "__key", "key", "__old", "__a")


def run_grid(spark: SparkSession, backends: dict[str, Callable[[], DataFrame]]) -> DataFrame:
    """The frames of several backends under each other, marked by ``backend_id``."""
    out = None
    for name, make in backends.items():
        part = make().withColumn("backend_id", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out if out is not None else spark.createDataFrame([], "backend_id string")
