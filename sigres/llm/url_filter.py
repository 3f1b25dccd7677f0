"""URL filter: sorted arrays of 64-bit digests, memory-mapped, probed by vectorised binary search.

The index of a rule list is three files: the sorted XXH64 digests of the entries, the offsets of
their strings, and the strings with their verdicts.  Every worker maps them read-only, so all
workers of a machine share one copy in the page cache.  A digest that is found counts only if the
stored string is the probed one, so two entries with one digest stay apart.

A rule is a host and the beginning of a path.  A URL is probed once for each suffix of its host at
a label boundary and each length that a rule's path has.  The longest rule wins.
"""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Callable, Iterable

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import SparkFiles
from pyspark.sql import DataFrame, SparkSession

from sigres.llm.batches import map_text

#: (host, path, verdict) of the contract's rules.
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
#: Hosts that the method blocks where no rule applies.
BLOCKED_HOSTS = ("spam-farm.example.org", "spam-farm.example.com", "spam-farm.example.net")
_SCHEMA = "page_id long, host string, path string, rule string, verdict string"
_UPPER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def split_url(url: str | None) -> tuple[str, str]:
    """Host and path; both empty for null or a text without ``://``."""
    _, sep, rest = (url or "").partition("://")
    if not sep:
        return "", ""
    end = min((i for i in (rest.find(c) for c in "/?#") if i >= 0), default=len(rest))
    tail = rest[end:]
    stop = min((i for i in (tail.find(c) for c in "?#") if i >= 0), default=len(tail))
    return rest[:end].translate(_UPPER), tail[:stop]


def digest(entry: str) -> int:
    return xxhash.xxh64_intdigest(entry.encode("utf-8", "surrogatepass"))


class DigestArray:
    """A read-only map from strings to one byte, in memory-mapped files of one folder."""

    def __init__(self, stem: str, at: Callable[[str], str] = str):
        self.keys = np.load(at(f"{stem}.keys.npy"), mmap_mode="r")
        self.ends = np.load(at(f"{stem}.ends.npy"), mmap_mode="r")
        self.blob = np.load(at(f"{stem}.blob.npy"), mmap_mode="r")
        self.values = np.load(at(f"{stem}.values.npy"), mmap_mode="r")

    @staticmethod
    def write(stem: str, entries: Iterable[tuple[str, int]], hasher: Callable[[str], int] = digest) -> list[str]:
        """Write the files; a repeated entry keeps its last value.  ``hasher`` is for tests."""
        items = sorted((hasher(k), k.encode("utf-8", "surrogatepass"), v) for k, v in dict(entries).items())
        parts = {
            "keys": np.array([i[0] for i in items], np.uint64),
            "ends": np.cumsum([0, *(len(i[1]) for i in items)]).astype(np.int64),
            "blob": np.frombuffer(b"".join(i[1] for i in items) or b"\0", np.uint8),
            "values": np.array([i[2] for i in items], np.uint8),
        }
        for name, values in parts.items():
            np.save(f"{stem}.{name}.npy", values)
        return [f"{stem}.{name}.npy" for name in parts]

    def find(self, entries: list[str], hasher: Callable[[str], int] = digest) -> np.ndarray:
        """The value of each entry, or -1."""
        out = np.full(len(entries), -1, np.int64)
        if not len(self.keys) or not entries:
            return out
        probes = np.fromiter((hasher(e) for e in entries), np.uint64, len(entries))
        at = np.searchsorted(self.keys, probes)
        for i in np.flatnonzero(self.keys[np.minimum(at, len(self.keys) - 1)] == probes):
            want, j = entries[i].encode("utf-8", "surrogatepass"), int(at[i])
            while j < len(self.keys) and self.keys[j] == probes[i]:
                if self.blob[self.ends[j]:self.ends[j + 1]].tobytes() == want:
                    out[i] = self.values[j]
                    break
                j += 1
        return out


def host_suffixes(host: str) -> list[str]:
    """The host and what follows each of its dots, longest first."""
    out, at = [host], host.find(".")
    while at >= 0:
        out.append(host[at + 1:])
        at = host.find(".", at + 1)
    return out


def ship(spark: SparkSession, entries: Iterable[tuple[str, int]], label: str) -> str:
    """Build the files on the driver and let Spark copy them to every executor; returns their stem."""
    stem = f"{label}-{uuid.uuid4().hex}"
    folder = tempfile.mkdtemp(prefix="sigres-urls-")
    for path in DigestArray.write(os.path.join(folder, stem), entries):
        spark.sparkContext.addFile(path)
    return stem


def filter_urls(pages: DataFrame, rules=RULES, blocked_hosts: Iterable[str] = BLOCKED_HOSTS) -> DataFrame:
    """One row per row of ``pages`` (page_id, url): page_id, host, path, rule, verdict.

    Without a rule the method blocks a URL whose host, or a domain above it, is on the host list.
    Null, empty and malformed URLs have empty host and path, fit no rule and are allowed.  Repeated
    rows are judged each; an empty table gives an empty result; other columns are not read.
    """
    spark = pages.sparkSession
    lengths = sorted({len(p) for _, p, _ in rules}, reverse=True)
    named = {f"{h}\0{p}": v == "block" for h, p, v in rules}
    ruled, listed = ship(spark, named.items(), "rules"), ship(spark, ((h, 1) for h in blocked_hosts), "hosts")

    def load():
        return DigestArray(ruled, SparkFiles.get), DigestArray(listed, SparkFiles.get)

    def judge(part: pa.RecordBatch, state) -> dict:
        by_rule, by_host = state
        split = [split_url(u) for u in part.column("url").to_pylist()]
        probes, owner, hosts, host_of = [], [], [], []
        for i, (host, path) in enumerate(split):
            if not host:
                continue
            for suffix in host_suffixes(host):
                hosts.append(suffix)
                host_of.append(i)
                for n in lengths:
                    if n <= len(path):
                        probes.append(f"{suffix}\0{path[:n]}")
                        owner.append(i)
        rule, verdict = [None] * len(split), ["allow"] * len(split)
        for j in np.flatnonzero(by_host.find(hosts) >= 0):
            verdict[host_of[j]] = "block"
        values = by_rule.find(probes)
        for j in np.flatnonzero(values >= 0):
            text = probes[j].replace("\0", "", 1)
            if rule[owner[j]] is None or len(text) > len(rule[owner[j]]):
                rule[owner[j]], verdict[owner[j]] = text, "block" if values[j] else "allow"
        return {"page_id": part.column("page_id"), "host": [s[0] for s in split], "path": [s[1] for s in split],
                "rule": rule, "verdict": verdict}

    return map_text(pages.select("page_id", "url"), judge, _SCHEMA, text="url", setup=load)


ORACLE = r"""
WITH u AS (
  SELECT page_id, CASE WHEN strpos(coalesce(url, ''), '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS r FROM pages
), p AS (
  SELECT page_id, translate(regexp_extract(r, '(?s)^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(substr(r, length(regexp_extract(r, '(?s)^[^/?#]*')) + 1), '(?s)^[^?#]*') AS path
  FROM u
), k(h, q, v) AS (VALUES ('net', '/', 'block'), ('example.net', '/en/', 'allow'), ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow')),
f AS (
  SELECT page_id, arg_max(h || q, length(h || q)) AS rule, arg_max(v, length(h || q)) AS v
  FROM p JOIN k ON (p.host = k.h OR ends_with(p.host, '.' || k.h)) AND starts_with(p.path, k.q) GROUP BY page_id
)
SELECT p.page_id, p.host, p.path, f.rule, coalesce(f.v, CASE WHEN p.host SIMILAR TO '(.*\.)?spam-farm\.example\.(org|com|net)' THEN 'block' ELSE 'allow' END) AS verdict
FROM p LEFT JOIN f USING (page_id)
"""
