"""Atomic batch commits on a file system with rename.

Tables of a batch are written under batch=<k>/<attempt>; then its manifest is written beside the manifests and renamed
to its number, which fails if there is one. Readers follow manifests and never list data, so a batch is visible
whole or not at all; a batch that has a manifest is a no-op when it comes again; losers and crashed
attempts leave files that no manifest names, which sweep() finds. A manifest names the tables of its whole chain, so
a read opens one manifest, however many batches there are. A manifest that can't be read (from a crashed writer of
another kind) counts as none and is replaced.
"""

from __future__ import annotations

import json
import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession


@dataclass
class Store:
    spark: SparkSession
    root: str

    def _fs(self, path: str):
        jvm = self.spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        return p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), p

    def _manifest(self, k: int) -> str:
        return f"{self.root}/manifests/{k:09d}.json"

    def manifest(self, k: int) -> dict | None:
        """Read through the file system, without a job; None if there is none, or none that is whole."""
        fs, p = self._fs(self._manifest(k))
        if not fs.exists(p):
            return None
        stream = fs.open(p)
        try:
            body = json.loads(self.spark.sparkContext._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        except ValueError:
            return None
        finally:
            stream.close()
        return body if isinstance(body, dict) and {"k", "parent", "paths", "chain"} <= body.keys() else None

    def _publish(self, k: int, body: dict) -> bool:
        """Write the manifest aside and rename it to its place; False if another one was first."""
        sc = self.spark.sparkContext
        fs, p = self._fs(self._manifest(k))
        fs.mkdirs(p.getParent())
        aside = sc._jvm.org.apache.hadoop.fs.Path(f"{self.root}/manifests/.{k:09d}-{uuid.uuid4().hex}.tmp")
        out = fs.create(aside, True)
        out.write(bytearray(json.dumps(body).encode()))
        out.close()
        torn = fs.exists(p) and self.manifest(k) is None
        kind = getattr(sc._jvm.org.apache.hadoop.fs, "Options$Rename")
        how = sc._gateway.new_array(kind, 1)
        how[0] = kind.OVERWRITE if torn else kind.NONE
        files = sc._jvm.org.apache.hadoop.fs.FileContext.getFileContext(fs.getUri(), sc._jsc.hadoopConfiguration())
        try:
            files.rename(fs.makeQualified(aside), fs.makeQualified(p), how)
            return True
        except Exception:
            if self.manifest(k) is None:
                raise
            return False
        finally:
            fs.delete(aside, False)

    def last(self) -> int:
        """Number of the newest batch, -1 if there is none."""
        fs, p = self._fs(f"{self.root}/manifests")
        names = [s.getPath().getName() for s in fs.listStatus(p)] if fs.exists(p) else []
        found = sorted((int(n[:9]) for n in names if n.endswith(".json") and n[:9].isdigit()), reverse=True)
        return next((k for k in found if self.manifest(k)), -1)

    def commit(self, k: int, tables: dict[str, DataFrame], note: str = "", parent: int | None = None) -> dict:
        """Publish the tables as batch k, once; the manifest that counts is returned."""
        if done := self.manifest(k):
            return done
        attempt = uuid.uuid4().hex
        paths = {}
        for name, df in tables.items():
            paths[name] = f"{self.root}/data/{name}/batch={k}/{attempt}"
            df.write.parquet(paths[name])
        parent = k - 1 if parent is None else parent
        before = (self.manifest(parent) or {"chain": {}})["chain"] if parent >= 0 else {}
        chain = {n: [*before.get(n, []), *([paths[n]] if n in paths else [])] for n in {**before, **paths}}
        body = {"k": k, "parent": parent, "paths": paths, "chain": chain, "note": note}
        return body if self._publish(k, body) else self.manifest(k)

    def chain(self, k: int | None = None) -> list[dict]:
        """Manifests from the first batch to k, along parents."""
        k = self.last() if k is None else k
        out = []
        while k >= 0 and (m := self.manifest(k)):
            out.append(m)
            k = m["parent"]
        return out[::-1]

    def read(self, name: str, k: int | None = None) -> DataFrame | None:
        """Rows of a table over all batches up to k."""
        newest = self.manifest(self.last() if k is None else k)
        paths = (newest or {"chain": {}})["chain"].get(name, [])
        return self.spark.read.parquet(*paths) if paths else None

    def rollback(self, k: int) -> dict:
        """A new batch whose parent is an older one; what came between stays on disk and in its manifests."""
        return self.commit(self.last() + 1, {}, note=f"rollback to {k}", parent=k)

    def sweep(self) -> list[str]:
        """Data folders that no manifest names."""
        named = {p for k in range(self.last() + 1) if (m := self.manifest(k)) for p in m["paths"].values()}
        fs, p = self._fs(f"{self.root}/data")
        if not fs.exists(p):
            return []
        found = [a.getPath().toString() for t in fs.listStatus(p) for b in fs.listStatus(t.getPath()) for a in fs.listStatus(b.getPath())]
        return sorted(f for f in found if not any(f.endswith(n.split("://")[-1].lstrip("/")) for n in named))
