"""Kept views: a snapshot and a log of deltas for each, on storage that all executors share."""

from __future__ import annotations

import json
import re
import tempfile
import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..operators.evaluate import inner_view, leaf_view
from ..operators.rings import Ring, View
from ..plans.tree import ViewNode, ViewTree


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or the checkpoint folder set on the context. A local
    master may go without, as its executors see the driver's files; a cluster may not."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if where:
        return where.rstrip("/")
    if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    where = tempfile.mkdtemp(prefix="deltaring-")
    spark.sparkContext.setCheckpointDir(where)
    return where


def new_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/deltaring/{name}-{uuid.uuid4().hex[:12]}"


class Files:
    """The few file operations the store needs, through Hadoop's file systems."""

    def __init__(self, spark: SparkSession):
        self.jvm, self.conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()

    def _at(self, path: str):
        p = self.jvm.org.apache.hadoop.fs.Path(path)
        return p.getFileSystem(self.conf), p

    def exists(self, path: str) -> bool:
        fs, p = self._at(path)
        return fs.exists(p)

    def write(self, path: str, text: str) -> None:
        """A new file, seen whole or not at all; FileExistsError if it is there."""
        fs, p = self._at(path)
        draft = self.jvm.org.apache.hadoop.fs.Path(f"{path.rsplit('/', 1)[0]}/.draft-{uuid.uuid4().hex}")
        out = fs.create(draft, True)
        out.write(bytearray(text.encode()))
        out.close()
        if fs.exists(p) or not fs.rename(draft, p):
            fs.delete(draft, False)
            raise FileExistsError(path)

    def read(self, path: str) -> str:
        fs, p = self._at(path)
        stream = fs.open(p)
        text = self.jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        stream.close()
        return text

    def remove(self, path: str) -> None:
        fs, p = self._at(path)
        fs.delete(p, True)


@dataclass(frozen=True)
class Commit:
    """A bulk that counts: its place in the order of commits (1 is the first) and the deltas it wrote."""

    place: int
    batch: str
    deltas: tuple[str, ...]


class ViewStore:
    """Views of a tree under a ring, kept as snapshot plus committed deltas.

    Layout: <path>/<view>/snapshot=<k>, <path>/<view>/delta/<batch>.<table>, <path>/pointer/<k> (the last one
    counts: the snapshot of each view and the place of the last commit in it), <path>/committed/<place> (the
    bulk and its deltas). Places count up from 1; bulks are ordered by the places of their commits, never by
    their names, which may be any words of letters, figures, ".", "_" and "-". A bulk counts once its marker is
    written, with exactly the deltas the marker names; one that broke off is written over when it comes again,
    one that is committed is not applied again. One writer at a time: a commit whose place is taken
    fails. Readers may name a bulk to read the state as of its commit (back to the snapshot).
    """

    def __init__(self, spark: SparkSession, tree: ViewTree, ring: Ring, path: str | None = None, updatable: tuple[str, ...] | None = None):
        self.spark, self.tree, self.ring, self.files = spark, tree, ring, Files(spark)
        self.path = path or new_folder(spark, "views")
        self.kept = {n.name: n for n in tree.materialised(updatable)}
        self.staged: list[str] = []
        self.schemas: dict = {}
        self._commits: list[Commit] = []
        self._pointer: tuple[int, dict] = (-1, {})

    def initialise(self, tables: dict[str, DataFrame]) -> ViewStore:
        """Compute the kept views from the tables, each from the stored ones below it."""
        for node in self.tree.nodes():
            if node.name in self.kept:
                self._snapshot(node, self._fresh(node, tables), 0)
        self._point(0, {n: {"snapshot": 0, "after": 0} for n in self.kept})
        return self

    def _fresh(self, node: ViewNode, tables: dict[str, DataFrame]) -> View:
        if node.alias is not None:
            return leaf_view(node, self.tree, self.ring, tables[node.alias])
        children = []
        for c in node.children:
            stored = self.files.exists(f"{self.path}/{c.name}/snapshot=0")
            children.append(View(self.spark.read.schema(self.schemas[c.name]).parquet(f"{self.path}/{c.name}/snapshot=0"), c.keys, c.attrs) if stored else self._fresh(c, tables))
        return inner_view(node, self.ring, children)

    def _columns(self, view: View) -> DataFrame:
        return view.df.select(*view.keys, *self.ring.payload(view.attrs))

    def _snapshot(self, node: ViewNode, view: View, k: int) -> None:
        df = self._columns(view)
        self.schemas[node.name] = df.schema
        df = df.sortWithinPartitions(*view.keys) if view.keys else df.coalesce(1)
        df.write.mode("overwrite").parquet(f"{self.path}/{node.name}/snapshot={k}")

    def _point(self, k: int, pointer: dict) -> None:
        self.files.write(f"{self.path}/pointer/{k:012d}", json.dumps(pointer))

    def pointer(self) -> dict:
        while self.files.exists(path := f"{self.path}/pointer/{self._pointer[0] + 1:012d}"):
            self._pointer = self._pointer[0] + 1, json.loads(self.files.read(path))
        return self._pointer[1]

    def commits(self) -> list[Commit]:
        """In the order they were made. Each marker is read once."""
        while self.files.exists(path := f"{self.path}/committed/{len(self._commits) + 1:012d}"):
            marker = json.loads(self.files.read(path))
            self._commits.append(Commit(len(self._commits) + 1, marker["batch"], tuple(marker["deltas"])))
        return self._commits

    def committed(self) -> list[str]:
        return [c.batch for c in self.commits()]

    def is_committed(self, batch: str) -> bool:
        return batch in self.committed()

    def begin(self, batch: str) -> bool:
        """Start a bulk; False if it was committed before."""
        if not re.fullmatch(r"[A-Za-z0-9][A-Za-z0-9._-]*", batch):
            raise ValueError(f"no name of a bulk: {batch!r}")
        self.staged = []
        return not self.is_committed(batch)

    def append(self, node: ViewNode, batch: str, alias: str, view: View) -> tuple[View, int]:
        """Write a view's delta (over what an earlier try left); the delta as stored, and its rows, counted while written."""
        name = f"{batch}.{alias}"
        if name not in self.staged:
            self.staged.append(name)
        path = f"{self.path}/{node.name}/delta/{name}"
        df, rows = self._columns(view), Observation()
        df.observe(rows, F.count(F.lit(1)).alias("rows")).write.mode("overwrite").parquet(path)
        return View(self.spark.read.schema(df.schema).parquet(path), view.keys, view.attrs), rows.get["rows"]

    def commit(self, batch: str) -> None:
        """Take the place after the commits this store has seen."""
        try:
            self.files.write(f"{self.path}/committed/{len(self._commits) + 1:012d}", json.dumps({"batch": batch, "deltas": self.staged}))
        except FileExistsError:
            raise RuntimeError(f"another writer committed while bulk {batch} was computed; apply it again") from None
        self.staged = []

    @staticmethod
    def _place(until: str | int | None, commits: list[Commit]) -> int | None:
        if until is None or isinstance(until, int):
            return until
        found = [c.place for c in commits if c.batch == until]
        if not found:
            raise ValueError(f"bulk {until} is not committed")
        return found[0]

    def rows(self, node: ViewNode, until: str | int | None = None) -> View:
        """The view's rows, snapshot and deltas side by side, not merged: joins distribute over them.

        until: a bulk, or a place in the order of commits (0: the initial load); else all commits and what is staged.
        """
        at, commits = self.pointer()[node.name], self.commits()
        last = self._place(until, commits)
        if last is not None and last < at["after"]:
            raise ValueError(f"the snapshot of {node.name} already holds commit {at['after']}")
        wanted = {d for c in commits if c.place > at["after"] and (last is None or c.place <= last) for d in c.deltas} | (set(self.staged) if last is None else set())
        names = sorted(x for x in wanted if self._touches(x, node))
        paths = [f"{self.path}/{node.name}/snapshot={at['snapshot']}", *[f"{self.path}/{node.name}/delta/{x}" for x in names]]
        if node.name not in self.schemas:
            self.schemas[node.name] = self.spark.read.parquet(paths[0]).schema
        return View(self.spark.read.schema(self.schemas[node.name]).parquet(*paths), node.keys, node.attrs)

    def _touches(self, delta: str, node: ViewNode) -> bool:
        return any(n is node for n in self.tree.path(delta.rsplit(".", 1)[1]))

    def state(self, node: ViewNode | None = None, until: str | int | None = None) -> View:
        """The view merged, without keys whose payload is zero."""
        node = node or self.tree.root
        return self.ring.state(self.rows(node, until), node.keys)

    def compact(self) -> None:
        """New snapshots of all views; the pointer turns to them before the old files go. A bulk that was not
        committed by then is in no snapshot, whatever its name, and its deltas stay."""
        commits, old = list(self.commits()), self.pointer()
        last = commits[-1].place if commits else 0
        k = 1 + max(p["snapshot"] for p in old.values())
        new = {}
        for name, node in self.kept.items():
            self._snapshot(node, self.state(node, last), k)
            new[name] = {"snapshot": k, "after": last}
        self._point(k, new)
        for name, node in self.kept.items():
            self.files.remove(f"{self.path}/{name}/snapshot={old[name]['snapshot']}")
            for d in (d for c in commits if c.place > old[name]["after"] for d in c.deltas if self._touches(d, node)):
                self.files.remove(f"{self.path}/{name}/delta/{d}")

    def remove(self) -> None:
        """Delete all files of the store."""
        self.files.remove(self.path)
