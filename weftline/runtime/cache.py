"""Reuse of intermediates by content: fingerprints, a Parquet store, moments in memory."""

from __future__ import annotations

import hashlib
import json
import threading
import time
import uuid
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from ..operators.encoders import narrowed
from ..plans.ir import Dag, Node, canonical

#: Bytes in memory of a byte of Parquet, about.
EXPANSION = 4.0
TABLES = {"listing": ("lineitem", "part", "orders", "customer", "nation", "supplier")}


def source_state(spark: SparkSession, sf_dir: str, source: str) -> str:
    """Paths, sizes and times of the files behind a source."""
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    told = []
    from ..workloads.others import VIEWS

    for t in TABLES.get(source) or (VIEWS[source][1] if source in VIEWS else (source,)):
        path = jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/{t}.parquet")
        fs = path.getFileSystem(conf)
        files = fs.listFiles(path, True)
        while files.hasNext():
            f = files.next()
            told.append((f.getPath().toString(), f.getLen(), f.getModificationTime()))
    return json.dumps(sorted(told))


@dataclass
class Fingerprints:
    """Hashes of a node with the state of its sources, computed once a node."""

    spark: SparkSession
    sf_dir: str
    known: dict[str, str] = field(default_factory=dict)

    def of(self, node: Node) -> str:
        if node.key not in self.known:
            own = source_state(self.spark, self.sf_dir, node.params["source"]) if node.op == "READ" else ""
            # what a preparation is fitted on and how stands in its parameters, whatever fits it was merged with
            inputs = node.inputs[:1] if node.op == "APPLY_PREP" else node.inputs
            told = json.dumps([node.op, node.version, canonical(node.params), node.seed, node.deterministic, own, [self.of(n) for n in inputs]])
            self.known[node.key] = hashlib.sha256(told.encode()).hexdigest()
        return self.known[node.key]


@dataclass
class Entry:
    path: str
    bytes: int
    seconds: float
    features: list[str]
    hits: int = 0
    used: float = 0.0
    frame: DataFrame | None = None
    kept: DataFrame | None = None
    written: bool = False
    in_memory: bool = True
    expected: float = 0.0


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share; where none is set, a temporary one on one machine, else the warehouse."""
    import tempfile

    told = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not told:
        alone = spark.sparkContext.master == "local" or spark.sparkContext.master.startswith("local[")
        told = tempfile.mkdtemp(prefix="weftline-") if alone else f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/weftline-shared"
        spark.sparkContext.setCheckpointDir(told)
    return told.rstrip("/")


class ReuseCache:
    """Frames of marked nodes, in memory first, then as Parquet under the shared folder.

    Frames stay persisted within a share of the memory for storage; what passes
    the share is kept as Parquet alone.  Files are written behind the run that
    made them (``settle``), so a run never waits for what may not be used again.
    A catalog file for each entry lets other sessions on the same root find it.
    Eviction takes the least value (seconds saved by hits a byte) or the least recently used.
    """

    def __init__(self, spark: SparkSession, sf_dir: str, *, share: float = 0.10, total_bytes: float | None = None, policy: str = "cost_size", tenant: str | None = None, most_files_bytes: float = 1e12):
        self.spark, self.policy = spark, policy
        self.budget, self.most_files = share * (total_bytes or storage_bytes(spark)), most_files_bytes
        self.shared = tenant is not None
        self.root = f"{shared_root(spark)}/reuse-{tenant or uuid.uuid4().hex}"
        self.prints = Fingerprints(spark, sf_dir)
        self.entries: dict[str, Entry] = {}
        self.states: dict[str, object] = {}
        self.stats = {"probes": 0, "hits": 0, "stored": 0, "evicted": 0, "bytes": 0, "shared_hits": 0}
        self.lock = threading.RLock()
        self.writer = ThreadPoolExecutor(1)
        self.waiting: list = []

    def _count(self, **more: int) -> None:
        with self.lock:
            for k, v in more.items():
                self.stats[k] += v

    def _fs(self, path: str):
        where = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        return where.getFileSystem(self.spark._jsc.hadoopConfiguration()), where

    def has(self, node: Node) -> bool:
        """Whether a probe or a look for a state will find the node, here or in the shared catalog."""
        if not node.cacheable or node.op not in ("APPLY_PREP", "MOMENTS", "FIT_TREES"):
            return False
        print_ = self.prints.of(node)
        with self.lock:
            return print_ in self.states or print_ in self.entries or (self.shared and node.op == "APPLY_PREP" and self._from_catalog(print_) is not None)

    def probe(self, node: Node) -> tuple[DataFrame, list[str]] | None:
        if not node.cacheable:
            return None
        self._count(probes=1)
        print_ = self.prints.of(node)
        with self.lock:
            entry = self.entries.get(print_) or self._from_catalog(print_)
            if entry is None:
                return None
            if entry.frame is None:
                try:
                    entry.frame = self.spark.read.parquet(entry.path)
                except Exception:  # a damaged entry is made anew
                    self.entries.pop(print_, None)
                    return None
            self.stats["hits"] += 1
            entry.hits, entry.used = entry.hits + 1, time.time()
            return entry.frame, entry.features

    def _from_catalog(self, print_: str) -> Entry | None:
        """An entry that another session wrote under this root."""
        fs, where = self._fs(f"{self.root}/catalog/{print_}.json")
        if not fs.exists(where):
            return None
        told = json.loads(self.spark.read.text(where.toString(), wholetext=True).first()[0])
        self.entries[print_] = Entry(told["path"], told["bytes"], told["seconds"], told["features"], used=time.time())
        self.stats["shared_hits"] += 1
        return self.entries[print_]

    def put(self, node: Node, df: DataFrame, features: list[str], seconds: float = 0.0, expected_bytes: float = 0.0) -> DataFrame:
        """Keeps a frame in memory and notes it to be written."""
        if not node.cacheable:
            return df
        kept, widened = narrowed(df)
        frame = widened(kept.persist())
        with self.lock:
            print_ = self.prints.of(node)
            self.entries[print_] = Entry(f"{self.root}/{uuid.uuid4().hex}", 0, seconds, features, used=time.time(), frame=frame, kept=kept, expected=expected_bytes)
            self.stats["stored"] += 1
            self.waiting.append(print_)
        return frame

    def settle(self, wait: bool = False) -> None:
        """Writes frames behind whatever comes next, where they pass the memory's share or others may use them.

        ``wait`` writes all and returns when they are there.
        """
        with self.lock:
            if not wait and not self.shared and sum(e.expected for e in self.entries.values() if e.in_memory) <= self.budget:
                return
            todo, self.waiting = self.waiting, []
        running = [self.writer.submit(self._write, p) for p in todo]
        if wait:
            for r in running:
                r.result()
            self.writer.submit(lambda: None).result()

    def _write(self, print_: str) -> None:
        entry = self.entries.get(print_)
        if entry is None or entry.frame is None:
            return
        began = time.time()
        entry.frame.write.parquet(entry.path)
        fs, where = self._fs(entry.path)
        entry.bytes = int(fs.getContentSummary(where).getLength())
        entry.seconds += time.time() - began
        told = json.dumps({"path": entry.path, "bytes": entry.bytes, "seconds": entry.seconds, "features": entry.features})
        _, catalog = self._fs(f"{self.root}/catalog/{print_}.json")
        try:
            out = fs.create(catalog, False)
            out.write(bytearray(told.encode()))
            out.close()
        except Exception:  # another session entered it first
            pass
        entry.written = True
        self._count(bytes=entry.bytes)
        self._evict()

    def _evict(self) -> None:
        """First out of memory, then off the disk."""
        worth = (lambda e: e.used) if self.policy == "lru" else (lambda e: e.seconds * (1 + e.hits) / max(1, e.bytes))
        with self.lock:
            held = [e for e in self.entries.values() if e.frame is not None and e.written and e.in_memory]
            while held and sum(e.bytes for e in held) * EXPANSION > self.budget:
                least = min(held, key=worth)
                held.remove(least)
                (least.kept or least.frame).unpersist()
                least.frame, least.kept, least.in_memory = None, None, False
                self.stats["evicted"] += 1
            while len(self.entries) > 1 and sum(e.bytes for e in self.entries.values()) > self.most_files:
                least = min((k for k, e in self.entries.items() if e.written), key=lambda k: worth(self.entries[k]), default=None)
                if least is None:
                    break
                entry = self.entries.pop(least)
                for path in (entry.path, f"{self.root}/catalog/{least}.json"):
                    fs, where = self._fs(path)
                    fs.delete(where, True)
                self.stats["evicted"] += 1

    def state(self, node: Node) -> object | None:
        """Small states (moments, solved models) by fingerprint."""
        found = self.states.get(self.prints.of(node)) if node.cacheable else None
        self._count(probes=1, hits=int(found is not None))
        return found

    def put_state(self, node: Node, value: object) -> None:
        if node.cacheable:
            self.states[self.prints.of(node)] = value


def storage_bytes(spark: SparkSession) -> float:
    """Memory for storage of all executors, as the session has it."""
    memory = spark.sparkContext._jsc.sc().getExecutorMemoryStatus()
    return float(sum(memory.apply(k)._1() for k in scala_list(memory.keySet().toSeq())))


def scala_list(seq) -> list:
    return [seq.apply(i) for i in range(seq.size())]


def mark_candidates(dag: Dag, seconds: dict[str, float], bytes_of: dict[str, float], stage: str = "explore", policy: str = "speculative", threshold: float = 0.5) -> list[str]:
    """Nodes worth keeping, the best first: the last preparation steps and what several sinks share."""
    prior = {"explore": 1.0, "exploit": 3.0}[stage]
    users = dag.consumers()
    out = []
    for n in dag.nodes():
        if n.op != "APPLY_PREP" or not n.cacheable:
            continue
        if policy == "greedy":
            if seconds.get(n.key, 0) >= threshold:
                out.append((seconds[n.key], n.key))
        else:
            out.append((seconds.get(n.key, 0) * (users.get(n.key, 1) + prior) / max(1.0, bytes_of.get(n.key, 1.0)), n.key))
    return [k for _, k in sorted(out, reverse=True)]
