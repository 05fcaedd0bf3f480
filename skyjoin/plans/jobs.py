"""Long matches as jobs: wedges of right ascension as independent steps that write staging tables, with a manifest.

A finished wedge is never redone. A failed one is tried again a limited number of times; a suspended job stops between wedges
(a running wedge is cancelled after its grace period) and resumes from its manifest. A failed or cancelled job removes what it
staged. The driver only issues plans; rows go from executors to files.
"""

from __future__ import annotations

import json
import math
import threading
import time
import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.sphere import ra_window
from .stats import wedge_of

VERSION = 1


class Suspended(Exception):
    pass


class Failed(Exception):
    pass


def anchor_slice(df: DataFrame, bounds: list[float], k: int, ra: str = "ra") -> DataFrame:
    """The anchor's rows of wedge k: every row is in exactly one wedge."""
    return df.filter((F.col(ra) >= bounds[k]) & (F.col(ra) < bounds[k + 1]) if k + 2 < len(bounds) else F.col(ra) >= bounds[k])


def partner_slice(df: DataFrame, bounds: list[float], k: int, radius_deg: float, ra: str = "ra", dec: str = "dec") -> DataFrame:
    """A partner's rows that can match an anchor of wedge k: the wedge and its margin, wider towards the poles."""
    half = ra_window(dec, radius_deg)
    width = bounds[k + 1] - bounds[k]
    off = F.pmod(F.col(ra) - bounds[k] + half, F.lit(360.0))
    return df.filter((half * 2 + width >= 360.0) | (off <= width + 2 * half))


@dataclass
class Job:
    """steps: wedge number -> a DataFrame to stage. The manifest and the staged wedges lie under root, in the job's own folder."""

    spark: SparkSession
    root: str
    step: Callable[[int], DataFrame]
    wedges: int
    retries: int = 2
    slots: int = 4
    job_id: str = field(default_factory=lambda: uuid.uuid4().hex[:12])
    version: int = VERSION
    redone: int = 0
    seconds: dict[int, float] = field(default_factory=dict)
    active: set[int] = field(default_factory=set)
    suspended: threading.Event = field(default_factory=threading.Event)

    @property
    def folder(self) -> str:
        return f"{self.root}/job-{self.job_id}"

    def _path(self, name: str):
        jvm = self.spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{name}" if name else self.folder)
        return path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), path

    def _write(self, name: str, value: dict) -> None:
        fs, path = self._path(name)
        out = fs.create(path, True)
        out.write(bytearray(json.dumps(value).encode()))
        out.close()

    def done(self) -> set[int]:
        """Wedges with a manifest entry of this version; another version refuses to resume."""
        fs, path = self._path("manifest")
        if not fs.exists(path):
            return set()
        out = set()
        for f in fs.listStatus(path):
            stem = f.getPath().getName().removesuffix(".json")
            wedge, _, version = stem.partition("-v")
            if int(version) != self.version:
                raise Failed(f"the manifest is of version {version}, not {self.version}")
            out.add(int(wedge))
        return out

    def _one(self, k: int) -> None:
        for attempt in range(self.retries + 1):
            if self.suspended.is_set():
                raise Suspended
            self.spark.sparkContext.addJobTag(f"job-{self.job_id}")
            began = time.time()
            self.active.add(k)
            try:
                self.step(k).write.mode("overwrite").parquet(f"{self.folder}/wedge={k}")
                self._write(f"manifest/{k}-v{self.version}.json", {"wedge": k, "attempt": attempt, "at": time.time()})
                self.seconds[k] = time.time() - began
                return
            except Exception as error:
                self.redone += 1
                if self.suspended.is_set():
                    raise Suspended from error
                if attempt == self.retries:
                    raise Failed(f"wedge {k} failed {attempt + 1} times: {str(error)[:200]}") from error
            finally:
                self.active.discard(k)

    def run(self) -> DataFrame:
        """All wedges that are not done yet, then the staged result."""
        todo = sorted(set(range(self.wedges)) - self.done())
        try:
            with ThreadPoolExecutor(self.slots) as pool:
                for f in [pool.submit(self._one, k) for k in todo]:
                    f.result()
        except Suspended:
            raise
        except BaseException:
            self.cleanup()
            raise
        return self.result()

    def result(self) -> DataFrame:
        return self.spark.read.parquet(*[f"{self.folder}/wedge={k}" for k in sorted(self.done())])

    def suspend(self, grace: float = 0.0) -> None:
        """No new wedge starts; running ones are cancelled after the grace period and redone on resume."""
        self.suspended.set()
        if grace:
            time.sleep(grace)
        while self.active:  # a wedge that is still being planned has no job to cancel yet
            self.spark.sparkContext.cancelJobsWithTag(f"job-{self.job_id}")
            time.sleep(0.2)

    def redo_fraction(self) -> float:
        """Runs of wedges beyond the first, of all wedges."""
        return self.redone / self.wedges

    def resume(self) -> DataFrame:
        self.suspended.clear()
        return self.run()

    def cleanup(self) -> None:
        """Removes the job's own folder and nothing else."""
        fs, path = self._path("")
        if path.getName() == f"job-{self.job_id}":
            fs.delete(path, True)


def submit(job: Job, queue: str = "quick", limits: dict[str, float] | None = None) -> DataFrame:
    """Runs a job under its queue's time-out; past it the job is cancelled and its staging removed."""
    limit = ({"quick": 60.0, "long": 24 * 3600.0} | (limits or {}))[queue]
    job.spark.sparkContext.setLocalProperty("spark.scheduler.pool", queue)
    timer = threading.Timer(limit, job.suspend)
    timer.start()
    try:
        return job.run()
    except Suspended:
        job.cleanup()
        raise TimeoutError(f"queue {queue}: more than {limit:g} s") from None
    finally:
        timer.cancel()


def round_robin(wedges: int, slots: int) -> list[int]:
    """Slot of each wedge in turn; kept for comparison, as the scheduler places tasks here."""
    return [k % slots for k in range(wedges)]


def balanced(costs: list[float], slots: int) -> list[int]:
    """Slot of each wedge by largest cost first onto the least loaded slot."""
    load, out = [0.0] * slots, [0] * len(costs)
    for k in sorted(range(len(costs)), key=lambda k: -costs[k]):
        slot = min(range(slots), key=load.__getitem__)
        out[k], load[slot] = slot, load[slot] + costs[k]
    return out


def makespan(costs: list[float], slots: list[int]) -> float:
    load: dict[int, float] = {}
    for c, s in zip(costs, slots, strict=True):
        load[s] = load.get(s, 0.0) + c
    return max(load.values(), default=0.0)


def replicate_plan(copies: int) -> list[list[tuple[int, int]]]:
    """Rounds of (from, to) copies that double the mirrors each time."""
    out = []
    have = 1
    while have < copies:
        new = min(have, copies - have)
        out.append([(k, have + k) for k in range(new)])
        have += new
    assert len(out) == (math.ceil(math.log2(copies)) if copies > 1 else 0)
    return out


def by_wedges(anchor: DataFrame, partners: list[DataFrame], bounds: list[float], radius_deg: float, match: Callable[[DataFrame, list[DataFrame]], DataFrame], ra: str = "ra", dec: str = "dec") -> Callable[[int], DataFrame]:
    """A job's step: the match of one wedge's anchors with the partners around them."""
    return lambda k: match(anchor_slice(anchor, bounds, k, ra), [partner_slice(p, bounds, k, radius_deg, ra, dec) for p in partners])


def wedge_rows(df: DataFrame, bounds: list[float], ra: str = "ra") -> DataFrame:
    return df.withColumn("wedge", wedge_of(F.col(ra), bounds))
