"""Appending documents to a store: micro-batches are encoded with the dictionary in force, and the ratio is watched.

Each batch writes a folder of its own by batch id, so a batch that is run again replaces itself. The path is on a file system that the driver mounts. When the smoothed ratio exceeds the first by more than
``tau`` points the dictionary is extended by samples of the batch (old rows stay valid) while there is room for it, or else a rebuild is called for.
"""

from __future__ import annotations

import json
import os
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import dictionary as dic
from ..operators import factorize
from ..operators.collection import as_collection, with_offsets


@dataclass
class Monitor:
    """Ratio in points, smoothed."""

    tau: float = 1.0
    weight: float = 0.5
    first: float | None = None
    smooth: float | None = None

    def see(self, ratio: float) -> bool:
        """True when the ratio has drifted."""
        self.first = ratio if self.first is None else self.first
        self.smooth = ratio if self.smooth is None else self.weight * ratio + (1 - self.weight) * self.smooth
        return self.smooth - self.first > self.tau

    def reset(self) -> None:
        self.first = self.smooth = None


@dataclass
class Appender:
    spark: SparkSession
    path: str
    dictionary: dic.Dictionary
    codec: str = "ZV"
    s: int = 512
    m_extra: int = 4096
    m_limit: int = 1 << 30
    monitor: Monitor = field(default_factory=Monitor)
    log: list[dict] = field(default_factory=list)

    def _done(self, batch: int) -> str:
        return os.path.join(self.path, f"batch={batch}")

    def _before(self, batch: int) -> None:
        """The state that the batch first met: a batch that is run again is measured once, by the dictionary of its first run."""
        self.log = [x for x in self.log if x["batch"] < batch]
        if self.log:
            last = self.log[-1]
            self.monitor.first, self.monitor.smooth = last["first"], last["smooth"]
            if last["epoch"] == self.dictionary.epoch:
                sizes = self.dictionary.sizes[: last["next_version"] + 1]
                self.dictionary = dic.Dictionary(self.dictionary.data[: sizes[-1]], sizes, self.dictionary.epoch)

    def write_batch(self, docs: DataFrame, batch: int) -> None:
        """For ``foreachBatch``: docs has doc_id and text (or body). The log is replaced last and is what counts as done."""
        coll = as_collection(docs, "doc_id", "body" if "body" in docs.columns else "text")
        if not coll.limit(1).count():
            return
        self._before(batch)
        version, epoch = self.dictionary.version, self.dictionary.epoch
        enc = factorize.encode(coll, self.dictionary, self.codec)
        enc.write.mode("overwrite").parquet(self._done(batch))
        size = F.octet_length("pos_stream") + F.octet_length("len_stream")
        raw, coded = self.spark.read.parquet(self._done(batch)).agg(F.sum("n_bytes"), F.sum(size)).first()
        ratio, action = 100.0 * coded / max(raw, 1), "keep"
        if self.monitor.see(ratio):
            if len(self.dictionary.data) + self.m_extra <= self.m_limit:
                action = "extend"
                self.dictionary = dic.extend(self.dictionary, with_offsets(coll), self.m_extra, self.s)
            else:
                action = "rebuild"
            self.monitor.reset()
        self._commit({"batch": batch, "ratio": ratio, "action": action, "epoch": epoch, "dict_version": version, "next_version": self.dictionary.version, "first": self.monitor.first, "smooth": self.monitor.smooth})

    def _commit(self, entry: dict) -> None:
        self.dictionary.save(os.path.join(self.path, f"dictionary-{self.dictionary.epoch}"))
        self.log.append(entry)
        part = os.path.join(self.path, "log.json.part")
        with open(part, "w") as f:
            json.dump(self.log, f)
        os.replace(part, os.path.join(self.path, "log.json"))

    def rebuild(self, coll: DataFrame, spec: dic.DictSpec) -> None:
        """A fresh dictionary for everything so far, in a new epoch: all stored batches are replaced by one, and the monitor starts again.

        coll: the collection as it is now. Called when the log says ``rebuild``.
        """
        batch = self.log[-1]["batch"]
        self.dictionary, enc = rebuild(coll, spec, self.codec, self.dictionary.epoch + 1)
        where = os.path.join(self.path, f"epoch={self.dictionary.epoch}")
        enc.write.mode("overwrite").parquet(where)
        size = F.octet_length("pos_stream") + F.octet_length("len_stream")
        raw, coded = self.spark.read.parquet(where).agg(F.sum("n_bytes"), F.sum(size)).first()
        ratio = 100.0 * coded / max(raw, 1)
        self.monitor.reset()
        self.monitor.see(ratio)
        self._commit({"batch": batch, "ratio": ratio, "action": "rebuilt", "epoch": self.dictionary.epoch, "dict_version": 0, "next_version": 0, "first": ratio, "smooth": ratio})

    def store(self) -> DataFrame:
        """Rows that the dictionary in force reads: of its epoch's rebuild, if any, and of the batches after it."""
        epoch = self.dictionary.epoch
        folders = [self._done(x["batch"]) for x in self.log if x["action"] != "rebuilt" and x["epoch"] == epoch]
        folders += [os.path.join(self.path, f"epoch={epoch}")] if any(x["action"] == "rebuilt" and x["epoch"] == epoch for x in self.log) else []
        names = ["doc_id", "dict_version", "codec", "n_bytes", "n_factors", "pos_stream", "len_stream"]
        return self.spark.read.parquet(*folders).select(*names)

    def start(self, stream: DataFrame, checkpoint: str):
        return stream.writeStream.foreachBatch(self.write_batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def rebuild(coll: DataFrame, spec: dic.DictSpec, codec: str, epoch: int) -> tuple[dic.Dictionary, DataFrame]:
    """A fresh dictionary and the whole collection encoded by it; the new epoch's rows replace all older ones."""
    d = dic.build(with_offsets(coll), spec)
    d.epoch = epoch
    return d, factorize.encode(coll, d, codec).withColumn("epoch", F.lit(epoch))


def ratio_drift(rows: DataFrame, group: str, weight: float = 0.5) -> DataFrame:
    """Streaming state of three numbers a group: how often it was seen, the first and the smoothed ratio. rows: group, ratio."""
    import pandas as pd

    def step(key, batches, state):
        n, first, smooth = state.get if state.exists else (0, None, None)
        for b in batches:
            for r in b["ratio"]:
                first = float(r) if first is None else first
                smooth = float(r) if smooth is None else weight * float(r) + (1 - weight) * smooth
                n += 1
        state.update((n, first, smooth))
        yield pd.DataFrame({"grp": [key[0]], "n": [n], "first": [first], "smooth": [smooth]})

    keyed = rows.select(F.col(group).cast("string").alias("grp"), F.col("ratio").cast("double").alias("ratio"))
    return keyed.groupBy("grp").applyInPandasWithState(step, "grp string, n long, first double, smooth double", "n long, first double, smooth double", "update", "NoTimeout")
