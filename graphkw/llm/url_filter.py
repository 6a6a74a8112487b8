"""URL rules by a sorted digest array (operator 6).

A rule is a host and a path prefix. It fits its host and all subdomains where the
url's path starts with the rule's path; the longest fitting rule decides (of two
as long, the one with the longer host). The keys ``host + path`` are hashed with
64-bit xxhash and written as one sorted array beside the full strings, in the
shared folder; Spark hands that file to every executor, whose workers map it into
memory, so all workers of a machine share its pages. For each batch of urls all
possible keys (host suffixes times path prefixes of the lengths in use) are
probed by one vectorised binary search, and each hit is confirmed by its string.

The rule list is an input of its own, not derived from the corpus; ``max_bytes``
bounds the file. Urls that no rule fits get ``default``.

Edge cases: a null url or one without ``://`` has empty host and path and fits no
rule; repeated rows are judged each; further columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import SparkFiles
from pyspark.sql import DataFrame, SparkSession

from .base import map_batches, shared_dir, table

#: Fixed values: (verdict, host, path) of the production list.
RULES = (
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
)
SCHEMA = "page_id long, host string, path string, rule string, verdict string"
_UPPER = {c: c + 32 for c in range(ord("A"), ord("Z") + 1)}


def split_url(url: str | None) -> tuple[str, str]:
    """Host (A-Z lower-cased) and path; both empty without ``://``."""
    if not url or (at := url.find("://")) < 0:
        return "", ""
    rest = url[at + 3 :]
    end = min((k for c in "?#" if (k := rest.find(c)) >= 0), default=len(rest))
    rest = rest[:end]
    slash = rest.find("/")
    host, path = (rest, "") if slash < 0 else (rest[:slash], rest[slash:])
    return host.translate(_UPPER), path


def key_of(host: str, path: str) -> bytes:
    return host.encode("utf-8", "surrogatepass") + b"\0" + path.encode("utf-8", "surrogatepass")


def build_array(rules: Iterable[tuple[str, str, str]], max_bytes: int = 1 << 30) -> bytes:
    """The array file: counts, path lengths, then sorted digests, string ends, verdict bits and the strings."""
    entries: dict[bytes, bool] = {}
    for verdict, host, path in rules:
        if verdict not in ("allow", "block"):
            raise ValueError(f"no such verdict: {verdict}")
        entries[key_of(host.translate(_UPPER), path)] = verdict == "block"
    keys = sorted(entries, key=lambda k: (xxhash.xxh64_intdigest(k), k))
    lengths = sorted({len(k.split(b"\0", 1)[1].decode("utf-8", "surrogatepass")) for k in keys})
    parts = [
        np.array([len(keys), len(lengths), *lengths], "<u8"),
        np.array([xxhash.xxh64_intdigest(k) for k in keys], "<u8"),
        np.cumsum([len(k) for k in keys], dtype="<u8") if keys else np.empty(0, "<u8"),
        np.array([entries[k] for k in keys], "<u8"),
    ]
    data = b"".join(p.tobytes() for p in parts) + b"".join(keys)
    if len(data) > max_bytes:
        raise ValueError(f"the rules take {len(data)} bytes, more than {max_bytes}: split them over several passes")
    return data


class DigestArray:
    """The array file, mapped into memory and searched."""

    def __init__(self, raw: np.ndarray):
        n, m = (int(x) for x in raw[:16].view("<u8"))
        words = raw[: 8 * (2 + m + 3 * n)].view("<u8")
        self.lengths = [int(x) for x in words[2 : 2 + m]]
        self.keys, self.ends, self.block = (words[2 + m + k * n : 2 + m + (k + 1) * n] for k in range(3))
        self.strings = raw[8 * (2 + m + 3 * n) :]

    @classmethod
    def map(cls, path: str) -> DigestArray:
        return cls(np.memmap(path, np.uint8, "r"))

    def find(self, keys: list[bytes]) -> list[int]:
        """Entry of each key, or -1."""
        digests = np.fromiter((xxhash.xxh64_intdigest(k) for k in keys), "<u8", len(keys))
        at = np.searchsorted(self.keys, digests)
        out = [-1] * len(keys)
        maybe = np.flatnonzero(self.keys[np.minimum(at, len(self.keys) - 1)] == digests) if len(self.keys) else ()
        for k in maybe:
            i = int(at[k])
            while i < len(self.keys) and self.keys[i] == digests[k]:  # equal digests of different strings stand together
                start = int(self.ends[i - 1]) if i else 0
                if self.strings[start : int(self.ends[i])].tobytes() == keys[k]:
                    out[k] = i
                    break
                i += 1
        return out

    def candidates(self, host: str, path: str) -> Iterator[tuple[str, str]]:
        """Keys that could fit, longest first."""
        hosts = [host] if host else []
        at = -1
        while host and (at := host.find(".", at + 1)) >= 0:
            hosts.append(host[at + 1 :])
        pairs = [(h, path[:n]) for h in hosts for n in self.lengths if n <= len(path)]
        yield from sorted(pairs, key=lambda p: (len(p[0]) + len(p[1]), len(p[0])), reverse=True)


def publish(spark: SparkSession, data: bytes) -> str:
    """Puts the array into the shared folder and has Spark hand it to all executors; returns the file's name."""
    name = f"digests-{hashlib.sha256(data).hexdigest()[:24]}.bin"
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/{name}")
    fs = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if not fs.exists(path):
        out = fs.create(path, True)
        for k in range(0, len(data), 1 << 24):
            out.write(bytearray(data[k : k + (1 << 24)]))
        out.close()
    spark.sparkContext.addFile(fs.makeQualified(path).toString())
    return name


def filter_urls(pages: DataFrame, rules: Iterable[tuple[str, str, str]] = RULES, default: str = "allow") -> DataFrame:
    """One row per page: host, path, the rule that decided (or null) and the verdict."""
    name = publish(pages.sparkSession, build_array(rules))

    def make():
        array = DigestArray.map(SparkFiles.get(name))

        def work(batch):
            parts = [split_url(u) for u in batch.column(1).to_pylist()]
            seen = dict.fromkeys(parts)
            tries = [(p, c) for p in seen for c in array.candidates(*p)]
            for (p, c), i in zip(tries, array.find([key_of(*c) for _, c in tries]), strict=True):
                if i >= 0 and seen[p] is None:
                    seen[p] = ("".join(c), "block" if array.block[i] else "allow")
            found = [seen[p] or (None, default) for p in parts]
            columns = [batch.column(0), *(pa.array([x[k] for x in rows], pa.string()) for rows in (parts, found) for k in (0, 1))]
            yield pa.RecordBatch.from_arrays(columns, ["page_id", "host", "path", "rule", "verdict"])

        return work

    return map_batches(pages.select(pages["page_id"].cast("long").alias("page_id"), "url"), make, SCHEMA)


def op6_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return filter_urls(table(spark, sf_dir, "pages"))


OP6_SQL = r"""
WITH parts AS (
  SELECT page_id,
         coalesce(translate(regexp_extract(url, '^[\s\S]*?://([^/?#]*)([^?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
         coalesce(regexp_extract(url, '^[\s\S]*?://([^/?#]*)([^?#]*)', 2), '') AS path
  FROM pages),
rules(verdict, rhost, rpath) AS (VALUES ('allow', 'com', '/'), ('block', 'example.com', '/en/'), ('allow', 'www.example.com', '/en/'), ('block', 'net', '/es/'), ('block', 'net', '/fr/')),
fits AS (
  SELECT p.page_id, r.verdict, r.rhost || r.rpath AS rule,
         row_number() OVER (PARTITION BY p.page_id ORDER BY length(r.rhost || r.rpath) DESC, length(r.rhost) DESC) AS k
  FROM parts p JOIN rules r ON (p.host = r.rhost OR ends_with(p.host, '.' || r.rhost)) AND starts_with(p.path, r.rpath))
SELECT p.page_id, p.host, p.path, f.rule, coalesce(f.verdict, 'allow') AS verdict
FROM parts p LEFT JOIN fits f ON f.page_id = p.page_id AND f.k = 1
"""
