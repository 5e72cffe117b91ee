"""URL rules in a memory-mapped, sorted array of 64-bit digests.

A rule is a host and the beginning of a path. Every URL offers the keys (host suffix, path prefix) for the
suffixes of its host and the prefix lengths that rules have; their xxhash64 digests are searched in the
sorted array, and a hit counts only if the stored string equals the key. The longest rule wins.

Defined cases: a null URL or one without ``://`` has an empty host and path and fits no rule; without a rule
the verdict is the default; one rule given both ways counts as blocked; repeated rows repeat their result;
no rules at all is allowed. The rule list is broadcast only up to ``MAX_RULE_BYTES``; beyond it ``judge``
joins on the digests instead.
"""

from __future__ import annotations

import os
import tempfile
from collections.abc import Iterable, Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from . import arrowtext as at

MAX_RULE_BYTES = 64 << 20

HOST = r"^.*?://([^/?#]*)"
PATH = r"^.*?://[^/?#]*([^?#]*)"


class DigestArray:
    """Sorted digests, and the strings and values in the same order, in one flat buffer that can be mapped."""

    def __init__(self, buffer: np.ndarray):
        self.n = int(buffer[:8].view(np.int64)[0])
        ends = 8 + 8 * self.n
        self.digests = buffer[8:ends].view(np.uint64)
        self.offsets = buffer[ends : ends + 8 * (self.n + 1)].view(np.int64)
        ends += 8 * (self.n + 1)
        self.values = buffer[ends : ends + self.n]
        self.heap = buffer[ends + self.n :]

    @staticmethod
    def pack(entries: dict[str, int]) -> bytes:
        """``entries``: string to a value of 0 to 255."""
        rows = sorted((xxhash.xxh64_intdigest(k.encode()), k.encode(), v) for k, v in entries.items())
        offsets = np.cumsum([0, *(len(k) for _, k, _ in rows)]).astype(np.int64)
        digests = np.array([d for d, _, _ in rows], np.uint64)
        return b"".join([np.int64(len(rows)).tobytes(), digests.tobytes(), offsets.tobytes(), bytes(v for _, _, v in rows), *(k for _, k, _ in rows)])

    @staticmethod
    def mapped(blob: bytes, name: str) -> DigestArray:
        """The blob in a file of this process's temp folder, mapped; written once for each content."""
        path = Path(tempfile.gettempdir(), f"digests-{name}-{os.getpid()}")
        if not path.exists():
            path.parent.mkdir(parents=True, exist_ok=True)
            half = path.with_suffix(f".{os.urandom(4).hex()}")
            half.write_bytes(blob)
            half.rename(path)
        return DigestArray(np.memmap(path, np.uint8, "r"))

    def find(self, keys: list[bytes]) -> np.ndarray:
        """Position of every key, or -1."""
        found = np.full(len(keys), -1)
        if not self.n or not keys:
            return found
        digests = np.fromiter(map(xxhash.xxh64_intdigest, keys), np.uint64, len(keys))
        pos = np.searchsorted(self.digests, digests)
        todo = np.flatnonzero((pos < self.n) & (self.digests[np.minimum(pos, self.n - 1)] == digests))
        for i in todo:  # only real hits and collisions come here
            p = pos[i]
            while p < self.n and self.digests[p] == digests[i]:
                if self.string(p) == keys[i]:
                    found[i] = p
                    break
                p += 1
        return found

    def string(self, p: int) -> bytes:
        return self.heap[self.offsets[p] : self.offsets[p + 1]].tobytes()


def suffixes(host: str) -> Iterator[str]:
    yield host
    at_dot = host.find(".")
    while at_dot >= 0:
        host = host[at_dot + 1 :]
        yield host
        at_dot = host.find(".")


def lower_host(column):
    return F.translate(F.regexp_extract(column, f"(?s){HOST}", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def split(urls: DataFrame, url: str) -> DataFrame:
    """The frame with host (A-Z in lower case) and path."""
    text = F.coalesce(F.col(url), F.lit(""))
    return urls.withColumns({"host": lower_host(text), "path": F.regexp_extract(text, f"(?s){PATH}", 1)})


def judge(urls: DataFrame, rules: Iterable[tuple[str, str, bool]], url: str = "url", keep: tuple[str, ...] = ("page_id",), default: str = "allow") -> DataFrame:
    """``keep``, host, path, rule and verdict of every row; rules: (host, path prefix, blocked)."""
    entries: dict[str, int] = {}
    for host, path, blocked in rules:
        entries[host + path] = max(entries.get(host + path, 0), int(blocked))
    lengths = sorted({len(k) - k.find("/") if "/" in k else 0 for k in entries})
    parts = split(urls.select(*keep, F.col(url).alias("__url")), "__url").drop("__url")
    blob = DigestArray.pack(entries)
    if len(blob) > MAX_RULE_BYTES:
        return _judge_by_join(parts, entries, lengths, default)
    shared = urls.sparkSession.sparkContext.broadcast((blob, f"{xxhash.xxh64_hexdigest(blob)}"))
    schema = StructType(list(parts.schema.fields)).add("rule", "string").add("verdict", "string")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = DigestArray.mapped(*shared.value)
        for batch in batches:
            for part in at.blocks(batch, "path", 1 << 20):
                keys, owner = [], []
                hosts, paths = part.column("host").to_pylist(), part.column("path").to_pylist()
                for i, (host, path) in enumerate(zip(hosts, paths, strict=True)):
                    ends = [path[:n] for n in lengths if n <= len(path)]
                    for name in suffixes(host) if host else ():
                        for end in ends:
                            keys.append((name + end).encode())
                            owner.append(i)
                best = np.full(part.num_rows, -1)
                size = np.zeros(part.num_rows, np.int64)
                for i, p in zip(owner, table.find(keys), strict=True):
                    if p >= 0 and (n := int(table.offsets[p + 1] - table.offsets[p])) > size[i]:
                        best[i], size[i] = p, n
                rule = [table.string(p).decode() if p >= 0 else None for p in best]
                verdict = [default if p < 0 else "block" if table.values[p] else "allow" for p in best]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(rule, pa.string()), pa.array(verdict, pa.string())], names=[*part.schema.names, "rule", "verdict"])

    return parts.mapInArrow(run, schema)


def _judge_by_join(parts: DataFrame, entries: dict[str, int], lengths: list[int], default: str) -> DataFrame:
    """The same for lists too large to broadcast: distinct (host, path) pairs offer their keys to a join."""
    spark = parts.sparkSession
    rules = spark.createDataFrame(list(entries.items()), "rule string, blocked int").withColumn("d", F.xxhash64("rule"))
    labels = F.split("host", r"\.")
    names = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    ends = F.filter(F.array(*[F.lit(n) for n in lengths] or [F.lit(0)]), lambda n: n <= F.length("path"))
    keys = F.flatten(F.transform(names, lambda h: F.transform(ends, lambda n: F.concat(h, F.expr("path").substr(F.lit(1), n)))))
    pairs = parts.select("host", "path").where("host != ''").distinct().withColumn("key", F.explode(keys)).withColumn("d", F.xxhash64("key"))
    hits = pairs.join(rules, "d").where("key = rule")
    best = hits.groupBy("host", "path").agg(F.max_by(F.struct("rule", "blocked"), F.length("rule")).alias("b"))
    out = parts.join(best, ["host", "path"], "left")
    verdict = F.when(F.col("b").isNull(), default).when(F.col("b.blocked") == 1, "block").otherwise("allow")
    return out.select(*parts.columns, F.col("b.rule").alias("rule"), verdict.alias("verdict"))
