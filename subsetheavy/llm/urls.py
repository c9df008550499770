"""URL filter over a sorted digest array.

Allow and block entries are (host, path start). Each entry's host + path is kept as its 64-bit xxhash in one ascending
array with the full strings beside it, in a file that every executor gets and memory-maps. An url is probed with every
(parent host, path start of a length that some entry has) by one vectorised binary search for a whole batch, and a hit
counts only if the stored string equals the probe, so a collision of digests changes nothing. Among the entries that
fit, rules go before listed entries, the longest wins, then the longer host.

An entry fits its host and all subdomains if the url's path starts with its path. The host is what follows the first
`://` up to `/`, `?`, `#` or the end, A-Z lower-cased; the path what follows up to `?`, `#` or the end. Null urls and
urls without `://` have an empty host and path, match nothing and are allowed.
"""

from __future__ import annotations

import hashlib
import mmap
import os
import struct
import tempfile
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import SparkFiles
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: (host, path, allow?) of the contract, then host names under which whole sites are blocked where no rule fits.
RULES = (("org", "/", True), ("example.org", "/es/", False), ("example.org", "/en/1", False), ("com", "/fr/", True), ("com", "/de/", False))
BLOCKED = tuple(f"{name}.example.{top}" for name in ("ads-track", "spam-farm", "casino-win", "adult-x", "cheap-pills", "free-bets") for top in ("com", "net", "org"))
_UPPER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
_HEAD = struct.Struct("<4sIQQ")
_sent: set[tuple[str, str]] = set()


def pack(rules: Iterable[tuple[str, str, bool]], listed: Iterable[str]) -> bytes:
    """The filter file: header, digests ascending, string offsets, marks (1 allow, 2 rule), lengths of hosts, strings.
    Of equal strings the first rule stays."""
    entries: dict[bytes, tuple[int, int]] = {}
    for host, path, allow in rules:
        entries.setdefault((host.translate(_UPPER) + path).encode(), (2 + bool(allow), len(host.encode())))
    for host in listed:
        entries.setdefault(host.translate(_UPPER).encode(), (0, len(host.encode())))
    order = sorted(entries, key=lambda s: (xxhash.xxh64_intdigest(s), s))
    digests = np.array([xxhash.xxh64_intdigest(s) for s in order], np.uint64)
    offsets = np.concatenate([[0], np.cumsum([len(s) for s in order])]).astype(np.uint64)
    marks = np.array([entries[s] for s in order], np.uint32).reshape(-1, 2)
    starts = sorted({len(s.decode()) - len(s[: entries[s][1]].decode()) for s in order})
    return _HEAD.pack(b"URLF", 1, len(order), len(starts)) + digests.tobytes() + offsets.tobytes() + marks.tobytes() + np.array(starts, np.uint64).tobytes() + b"".join(order)


class Filter:
    """A packed filter over mapped bytes."""

    def __init__(self, held):
        mark, version, n, starts = _HEAD.unpack_from(held)
        if mark != b"URLF" or version != 1:
            raise ValueError("not a filter file")
        at = _HEAD.size
        self.digests = np.frombuffer(held, np.uint64, n, at)
        self.offsets = np.frombuffer(held, np.uint64, n + 1, at + 8 * n)
        self.marks = np.frombuffer(held, np.uint32, 2 * n, at + 16 * n + 8).reshape(n, 2)
        self.starts = np.frombuffer(held, np.uint64, starts, at + 24 * n + 8).tolist()
        self.held, self.base = held, at + 24 * n + 8 + 8 * starts

    @classmethod
    def open(cls, path: str) -> Filter:
        with open(path, "rb") as f:
            return cls(mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ))

    def string(self, i: int) -> bytes:
        return bytes(self.held[self.base + int(self.offsets[i]) : self.base + int(self.offsets[i + 1])])

    def judge(self, parts: list[tuple[str, str]]) -> list[tuple[str | None, bool]]:
        """(the rule that wins or None, allowed?) for each (host, path)."""
        probes, of = [], []
        for i, (host, path) in enumerate(parts):
            if not host:
                continue
            labels = host.split(".")
            for k in range(len(labels)):
                tail = ".".join(labels[k:])
                for n in self.starts:
                    if n <= len(path):
                        probes.append((tail + path[:n]).encode("utf-8", "surrogatepass"))
                        of.append((i, len(tail.encode("utf-8", "surrogatepass"))))
        best: list[tuple] = [(-1, 0, 0, None, True)] * len(parts)
        if len(self.digests) and probes:
            seen = np.array([xxhash.xxh64_intdigest(p) for p in probes], np.uint64)
            where = np.searchsorted(self.digests, seen)
            for j in np.flatnonzero(self.digests[np.minimum(where, len(self.digests) - 1)] == seen).tolist():
                at = int(where[j])
                while at < len(self.digests) and self.digests[at] == seen[j]:
                    mark, host_size = self.marks[at].tolist()
                    if host_size == of[j][1] and self.string(at) == probes[j]:
                        rule = mark >= 2
                        found = (int(rule), len(probes[j]), host_size, probes[j].decode() if rule else None, mark == 3)
                        best[of[j][0]] = max(best[of[j][0]], found, key=lambda x: x[:3])
                    at += 1
        return [(b[3], b[4]) for b in best]


def parts(url: str | None) -> tuple[str, str]:
    """(host, path) of an url."""
    if url is None or "://" not in url:
        return "", ""
    rest = url[url.index("://") + 3 :]
    end = min((i for i in map(rest.find, "?#") if i >= 0), default=len(rest))
    slash = rest.find("/", 0, end)
    host, path = (rest[:end], "") if slash < 0 else (rest[:slash], rest[slash:end])
    return host.translate(_UPPER), path


#: Hosts that a list may have: 100 million take some 4 GB of mapped file, which is what every executor gets.
MOST = 100_000_000


def listed_hosts(spark, path: str, col: str = "host", most: int = MOST) -> Iterator[str]:
    """The hosts of a table (Parquet, or text with one host a line), read part by part; a list of over `most` is refused."""
    table = spark.read.text(path).toDF(col) if path.endswith((".txt", ".gz")) else spark.read.parquet(path)
    hosts = table.select(F.trim(F.col(col)).alias(col)).where(F.length(col) > 0).distinct()
    n = hosts.count()
    if n > most:
        raise ValueError(f"{n} listed hosts, over {most}")
    return (r[0] for r in hosts.toLocalIterator())


def url_verdicts(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", rules: Iterable[tuple[str, str, bool]] = RULES, listed: Iterable[str] | str = BLOCKED) -> DataFrame:
    """(page_id, host, path, rule, verdict) for every row. listed: hosts whose whole sites are blocked, or the path of a
    table of them (see listed_hosts). The file goes to each executor once."""
    held = pack(rules, listed_hosts(pages.sparkSession, listed) if isinstance(listed, str) else listed)
    name = f"urls-{hashlib.sha256(held).hexdigest()[:16]}.bin"
    context = pages.sparkSession.sparkContext
    if (context.applicationId, name) not in _sent:  # a name can be sent once
        path = os.path.join(tempfile.mkdtemp(prefix="urls-"), name)
        with open(path, "wb") as f:
            f.write(held)
        context.addFile(path)
        _sent.add((context.applicationId, name))

    def work(batches):
        found = Filter.open(SparkFiles.get(name))
        for batch in batches:
            cut = [parts(u) for u in batch.column(1).to_pylist()]
            got = found.judge(cut)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(x, pa.string()) for x in ([c[0] for c in cut], [c[1] for c in cut], [g[0] for g in got], ["allow" if g[1] else "block" for g in got]))], names=["page_id", "host", "path", "rule", "verdict"])

    got = pages.select(F.col(id_col).cast("bigint").alias("page_id"), F.col(url_col).alias("url"))
    return got.mapInArrow(work, "page_id bigint, host string, path string, rule string, verdict string")
