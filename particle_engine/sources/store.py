"""State store: particles by run and cycle as Parquet, with a commit log.

Layout: ``<root>/<kind>/run_id=../cycle=../attempt=..`` and ``<root>/log`` (one JSON
row per commit).  Data of an attempt counts only once its commit row exists, so
a task or driver lost midway leaves nothing half-read, and a repeated attempt
never mixes with an earlier one.  States are committed before the weights that
vouch for them.
"""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession

LOG = "seq long, kind string, run_id string, cycle int, path string, payload string"


def shared_root(spark: SparkSession) -> str:
    """Folder that driver and executors share: the session's checkpoint folder; one of its own only in local mode, where none is set."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        import tempfile

        found = tempfile.mkdtemp(prefix="particle_engine_")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


class StateStore:
    """The log is read once and kept by the driver (a row per commit); ``refresh`` reads it again."""

    def __init__(self, spark: SparkSession, root: str | None = None):
        self.spark = spark
        self.root = (root or f"{shared_root(spark)}/store-{uuid.uuid4().hex}").rstrip("/")
        self.refresh()

    def _fs(self, path: str):
        p = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        return p.getFileSystem(self.spark._jsc.hadoopConfiguration()), p

    def manifest(self) -> DataFrame:
        """The commit log as a table."""
        fs, path = self._fs(f"{self.root}/log")
        return self.spark.read.schema(LOG).json(f"{self.root}/log") if fs.exists(path) else self.spark.createDataFrame([], LOG)

    def refresh(self) -> None:
        fs, path = self._fs(f"{self.root}/log")
        self.entries = [r.asDict() for r in self.manifest().orderBy("seq").collect()] if fs.exists(path) else []

    def commit(self, kind: str, run_id: str, cycle: int, path: str, payload: str = "") -> None:
        """Append one commit row, as a file of its own moved into place; the data must be written already."""
        entry = {"seq": self.entries[-1]["seq"] + 1 if self.entries else 1, "kind": kind, "run_id": run_id, "cycle": cycle, "path": path, "payload": payload}
        name = f"{entry['seq']:09d}-{uuid.uuid4().hex}.json"
        fs, part = self._fs(f"{self.root}/_pending-{name}")
        out = fs.create(part)
        out.write(bytearray((json.dumps(entry) + "\n").encode()))
        out.close()
        _, log = self._fs(f"{self.root}/log")
        fs.mkdirs(log)
        fs.rename(part, self._fs(f"{self.root}/log/{name}")[1])
        self.entries.append(entry)

    def committed(self, kind: str, run_id: str) -> list[int]:
        """Committed cycles, ascending."""
        return sorted({e["cycle"] for e in self.entries if e["kind"] == kind and e["run_id"] == run_id})

    def write(self, kind: str, run_id: str, cycle: int, df: DataFrame, payload: str = "") -> DataFrame:
        """Write a slice, commit it with a note, and return it re-read (lineage cut)."""
        if kind == "weights" and cycle not in self.committed("states", run_id):
            raise ValueError(f"weights of cycle {cycle} before its states")
        path = f"{self.root}/{kind}/run_id={run_id}/cycle={cycle}/attempt={uuid.uuid4().hex}"
        df.write.parquet(path)
        self.commit(kind, run_id, cycle, path, payload)
        return self.spark.read.schema(df.schema).parquet(path)

    def _last(self, kind: str, run_id: str, cycle: int | None = None) -> dict | None:
        found = [e for e in self.entries if e["kind"] == kind and e["run_id"] == run_id and cycle in (None, e["cycle"])]
        return found[-1] if found else None

    def note(self, kind: str, run_id: str, cycle: int) -> str:
        """The note of the newest committed attempt of a slice, empty where there is none."""
        last = self._last(kind, run_id, cycle)
        return last["payload"] if last else ""

    def read(self, kind: str, run_id: str, cycle: int) -> DataFrame:
        """The newest committed attempt of a slice."""
        last = self._last(kind, run_id, cycle)
        if last is None:
            raise KeyError((kind, run_id, cycle))
        return self.spark.read.parquet(last["path"])

    def resume_cycle(self, run_id: str) -> int | None:
        """Last cycle whose states and weights and offspring are all committed."""
        done = set(self.committed("states", run_id)) & set(self.committed("weights", run_id)) & set(self.committed("offspring", run_id))
        return max(done) if done else None

    def gc(self, run_id: str, keep_from: int) -> int:
        """Delete state slices of cycles before ``keep_from``; returns how many went."""
        gone = 0
        for e in self.entries:
            if e["kind"] == "states" and e["run_id"] == run_id and e["cycle"] < keep_from:
                fs, path = self._fs(e["path"])
                gone += bool(fs.delete(path, True))
        return gone

    def save_coordinator(self, run_id: str, cycle: int, state: dict) -> None:
        self.commit("coordinator", run_id, cycle, "", json.dumps(state, sort_keys=True))

    def load_coordinator(self, run_id: str) -> dict | None:
        last = self._last("coordinator", run_id)
        return json.loads(last["payload"]) if last else None

    def as_bucketed(self, df: DataFrame, name: str, buckets: int) -> DataFrame:
        """Bucketed table of states: reloads join on particle_id without a shuffle."""
        df.write.bucketBy(buckets, "particle_id").sortBy("particle_id").mode("overwrite").saveAsTable(name)
        return self.spark.table(name)
