"""View catalogue: versions on shared storage, epochs, refresh modes, outlier thresholds.

Each version is a directory that is written once. What is current is said by the newest
complete file of a numbered series of pointers, so readers see the old version until the
new one is complete, and a new manager goes on where another stopped (``load``).
"""

from __future__ import annotations

import json
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.hashing import SALT, Banded
from .operators.cleaning import stale_sample
from .operators.maintenance import refresh, refresh_sample, stale_plan
from .operators.outliers import threshold_sigma, threshold_topk
from .operators.views import View
from .sources.changes import ChangeSet
from .sources.tables import write_banded


@dataclass
class Entry:
    view: View
    m: float
    salt: str
    epoch: int = 0
    version: int = 0
    sample_version: int = 0
    #: Number of the newest pointer.
    pointer: int = 0
    #: Last logged batch that a full refresh has taken in.
    applied: int = -1
    thresholds: dict[str, float] = field(default_factory=dict)
    pending: list[ChangeSet] = field(default_factory=list)


class ViewManager:
    """Registers views, refreshes them eagerly or deferred, and keeps stale and fresh samples."""

    def __init__(self, spark: SparkSession, path: str) -> None:
        self.spark, self.path, self.entries = spark, path.rstrip("/"), {}

    def _dir(self, name: str, kind: str, version: int) -> str:
        return f"{self.path}/{name}/{kind}/v={version}"

    def register(self, view: View, changes: ChangeSet, m: float, salt: str = SALT) -> None:
        """Materialise the view from the old tables, by hash band, and cut its sample."""
        e = self.entries[view.name] = Entry(view, m, salt)
        try:
            before = self._newest(view.name)
            e.version, e.sample_version, e.pointer = before["version"], before["sample_version"], before["pointer"]
        except KeyError:
            pass
        self._publish(e, stale_plan(view, changes).lower())

    def load(self, view: View) -> None:
        """Take a registered view up again from its newest pointer; the definition itself is not stored."""
        state = self._newest(view.name)
        names = ("m", "salt", "epoch", "version", "sample_version", "applied", "thresholds", "pointer")
        self.entries[view.name] = Entry(view, **{n: state[n] for n in names})

    def _newest(self, name: str) -> dict:
        """The newest complete pointer."""
        folder = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}/pointer")
        files = folder.getFileSystem(self.spark._jsc.hadoopConfiguration())
        numbers = sorted((int(f.getPath().getName().split("=")[1]) for f in files.listStatus(folder)), reverse=True) if files.exists(folder) else []
        for n in numbers:
            if files.exists(self.spark._jvm.org.apache.hadoop.fs.Path(f"{folder}/n={n}/_SUCCESS")):
                return json.loads(self.spark.read.text(f"{folder}/n={n}").first()[0]) | {"pointer": n}
        raise KeyError(f"no complete pointer of {name}")

    def _publish(self, e: Entry, df: DataFrame) -> None:
        version = e.version + 1
        write_banded(df, self._dir(e.view.name, "view", version), list(e.view.keys), e.salt)
        e.version, e.epoch = version, e.epoch + 1
        self._publish_sample(e, self._cut(e))

    def _publish_sample(self, e: Entry, df: DataFrame) -> None:
        version = e.sample_version + 1
        df.write.mode("overwrite").parquet(self._dir(e.view.name, "sample", version))
        e.sample_version = version
        self._point(e)

    def _point(self, e: Entry) -> None:
        state = {"name": e.view.name, "key": list(e.view.keys), "m": e.m, "salt": e.salt, "epoch": e.epoch, "version": e.version, "sample_version": e.sample_version, "applied": e.applied, "thresholds": e.thresholds}
        e.pointer += 1
        self.spark.createDataFrame([(json.dumps(state),)], "state string").coalesce(1).write.mode("overwrite").text(f"{self.path}/{e.view.name}/pointer/n={e.pointer}")

    def _cut(self, e: Entry) -> DataFrame:
        """The stale sample by band: only the bands below m are read."""
        return stale_sample(self.stored(e.view.name), e.view.keys, e.m, e.salt)

    def stored(self, name: str) -> Banded:
        """The current view as it is stored, by hash band: plans over it read the bands below m for a sample."""
        e = self.entries[name]
        return Banded(self.spark.read.parquet(self._dir(name, "view", e.version)), tuple(e.view.keys), e.salt)

    def current(self, name: str) -> DataFrame:
        return self.stored(name).rows()

    def samples(self, name: str) -> tuple[DataFrame, DataFrame]:
        """Stale sample of the current epoch, and the latest fresh sample."""
        e = self.entries[name]
        return self._cut(e), self.spark.read.parquet(self._dir(name, "sample", e.sample_version))

    def apply(self, name: str, changes: ChangeSet, mode: str = "deferred") -> None:
        """Eager: refresh the view now. Deferred: refresh only the sample; ``refresh`` does the rest later.

        ``changes`` holds everything that is pending since the view's epoch began.
        """
        e = self.entries[name]
        if mode == "eager":
            self._publish(e, refresh(e.view, self.stored(name), changes))
            e.pending.clear()
            return
        e.pending = [changes]
        self._publish_sample(e, refresh_sample(e.view, self.stored(name), changes, e.m, e.salt))

    def refresh(self, name: str, new_salt: str | None = None, applied: int | None = None) -> None:
        """Full refresh with the pending changes; a new epoch may sample by a new salt. ``applied``: last logged batch among the changes."""
        e = self.entries[name]
        fresh = refresh(e.view, self.stored(name), e.pending[-1]) if e.pending else self.current(name)
        e.salt = new_salt or e.salt
        e.applied = e.applied if applied is None else applied
        self._publish(e, fresh)
        e.pending.clear()

    def retune_outliers(self, name: str, df: DataFrame, attr: str, rule: str = "topk", k: int = 100, c: float = 3.0) -> float:
        """Set the threshold of an attribute's outlier index anew."""
        e = self.entries[name]
        value = (threshold_topk(df, attr, k) if rule == "topk" else threshold_sigma(df, attr, c)).first()[0]
        e.thresholds[attr] = value
        self._point(e)
        return value

    def describe(self) -> DataFrame:
        rows = [(n, ",".join(e.view.keys), e.m, e.salt, e.epoch, len(e.pending)) for n, e in self.entries.items()]
        return self.spark.createDataFrame(rows, "name string, key string, m double, salt string, epoch int, pending int")

    def expose(self, name: str) -> None:
        """SQL views ``<name>``, ``<name>_stale_sample`` and ``<name>_fresh_sample``."""
        stale_s, fresh_s = self.samples(name)
        self.current(name).createOrReplaceTempView(name)
        stale_s.createOrReplaceTempView(f"{name}_stale_sample")
        fresh_s.createOrReplaceTempView(f"{name}_fresh_sample")

    def drop(self, name: str) -> None:
        """Forget a view; its files stay for readers that still hold them."""
        del self.entries[name]
        for suffix in ("", "_stale_sample", "_fresh_sample"):
            self.spark.catalog.dropTempView(name + suffix)


def answer(manager: ViewManager, name: str, q, level: float = 0.95, method: str | None = None) -> DataFrame:
    """estimate, low, high, k, level, method, m, epoch; the method is chosen by the paired moments if not given."""
    from .operators import bootstrap, intervals
    from .operators.estimate import LINEAR, choose_estimator

    e = manager.entries[name]
    stale_s, fresh_s = manager.samples(name)
    stale, key = manager.current(name), e.view.keys
    if method is None:
        method = choose_estimator(stale_s, fresh_s, q, e.m, key).first()["choice"] if q.agg in LINEAR else "correction"
    if q.agg in LINEAR or (method == "direct" and q.agg in ("avg", "ratio")):
        out = intervals.direct_interval(fresh_s, q, e.m, key, level) if method == "direct" else intervals.correction_interval(stale, stale_s, fresh_s, q, e.m, key, level)
    elif method == "direct":
        out = bootstrap.bootstrap_direct(fresh_s, q, e.m, key, level=level)
    else:
        out = bootstrap.bootstrap_correction(stale, stale_s, fresh_s, q, e.m, key, level=level)
    return out.select("estimate", "low", "high", F.lit(level).alias("level"), F.lit(method).alias("method"), F.lit(e.m).alias("m"), F.lit(e.epoch).alias("epoch"))
