"""Allow and block rules for URLs, looked up in a sorted digest array.

Every rule (a host and a path prefix) is one key string ``host + path``. The
keys' 64-bit xxhash digests are kept sorted in one file that each worker maps
into memory; the strings themselves lie beside it in the same order. A batch of
URLs turns into candidate keys (each suffix of the host that starts a label,
joined with each path prefix whose length some rule has), their digests are
found by one vectorised binary search, and a hit counts only if the stored
string equals the candidate, so digest collisions cannot decide anything.

The number of candidates of a URL is (labels of its host) x (distinct rule path
lengths) and does not depend on the number of rules. The rule file is shipped
through Spark's file distribution, so its size is bounded by a worker's disk
and page cache, not by its heap.
"""

from __future__ import annotations

import os
import tempfile
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import SparkFiles
from pyspark.sql import DataFrame

from pagecast.cluster import ship

ALLOW, BLOCK = "allow", "block"


@dataclass(frozen=True)
class Rule:
    host: str
    path: str
    verdict: str


class DigestArray:
    """Sorted digests with the full strings behind them, read through mmap.

    Layout: count and number of path lengths (u64 each), the path lengths,
    digests, string offsets (count + 1), host lengths (all u64), verdicts
    (u8), then the strings back to back.
    """

    def __init__(self, path: str):
        raw = np.memmap(path, np.uint8, "r")
        count, kinds = (int(x) for x in raw[:16].view(np.uint64))
        at = 16

        def take(n: int) -> np.ndarray:
            nonlocal at
            part = raw[at : at + 8 * n].view(np.uint64)
            at += 8 * n
            return part

        self.path_lengths = [int(x) for x in take(kinds)]
        self.digests, self.offsets, self.host_lengths = take(count), take(count + 1), take(count)
        self.verdicts, self.strings = raw[at : at + count], raw[at + count :]

    @staticmethod
    def write(rules: list[Rule], path: str) -> None:
        keyed = {}
        for rule in rules:
            if rule.verdict not in (ALLOW, BLOCK):
                raise ValueError(f"unknown verdict {rule.verdict!r}")
            key = (rule.host + rule.path).encode()
            if keyed.setdefault(key, rule).verdict != rule.verdict:
                raise ValueError(f"rules contradict each other: {rule.host + rule.path}")
        order = sorted((xxhash.xxh64_intdigest(key), key) for key in keyed)
        lengths = sorted({len(rule.path.encode()) for rule in rules})
        u64 = lambda xs: np.array(xs, np.uint64).tobytes()
        with open(path, "wb") as out:
            out.write(u64([len(order), len(lengths)]) + u64(lengths))
            out.write(u64([d for d, _ in order]))
            out.write(u64(np.cumsum([0, *(len(k) for _, k in order)])))
            out.write(u64([len(keyed[k].host.encode()) for _, k in order]))
            out.write(bytes(keyed[k].verdict == BLOCK for _, k in order))
            out.write(b"".join(k for _, k in order))

    def find(self, keys: list[bytes], host_lengths: list[int]) -> np.ndarray:
        """Position of each key, -1 where it is absent."""
        found = np.full(len(keys), -1, np.int64)
        if not len(self.digests) or not keys:
            return found
        wanted = np.fromiter(map(xxhash.xxh64_intdigest, keys), np.uint64, len(keys))
        first = np.searchsorted(self.digests, wanted, "left")
        last = np.searchsorted(self.digests, wanted, "right")
        for i in np.flatnonzero(last > first):
            for at in range(first[i], last[i]):
                if int(self.host_lengths[at]) == host_lengths[i] and self.string(at) == keys[i]:
                    found[i] = at
        return found

    def string(self, at: int) -> bytes:
        return self.strings[int(self.offsets[at]) : int(self.offsets[at + 1])].tobytes()


_LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def split_url(url: str | None) -> tuple[bytes, bytes]:
    """Host (A-Z lower-cased) and path; both empty without ``://``."""
    _, mark, rest = (url or "").encode("utf-8", "surrogatepass").partition(b"://")
    if not mark:
        return b"", b""
    end = min((at for at in map(rest.find, (b"/", b"?", b"#")) if at >= 0), default=len(rest))
    host, tail = rest[:end].translate(_LOWER), rest[end:]
    stop = min((at for at in map(tail.find, (b"?", b"#")) if at >= 0), default=len(tail))
    return host, tail[:stop]


def _judged(array: DigestArray, urls: list[str | None], default: str) -> tuple[list, list, list, list]:
    parts = [split_url(u) for u in urls]
    keys, host_lengths, owner = [], [], []
    for i, (host, path) in enumerate(parts):
        prefixes = [path[:n] for n in array.path_lengths if n <= len(path)]
        at = 0
        while host and at >= 0:
            suffix = host[at:]
            for prefix in prefixes:
                keys.append(suffix + prefix)
                host_lengths.append(len(suffix))
                owner.append(i)
            dot = host.find(b".", at)
            at = dot + 1 if dot >= 0 else -1
    found = array.find(keys, host_lengths)
    best: dict[int, tuple[int, int, int]] = {}
    for k in np.flatnonzero(found >= 0):
        rank = (len(keys[k]), host_lengths[k], int(found[k]))
        best[owner[k]] = max(best.get(owner[k], rank), rank)
    text = lambda b: b.decode("utf-8", "surrogatepass")
    rules = [text(array.string(best[i][2])) if i in best else None for i in range(len(urls))]
    verdicts = [(BLOCK if array.verdicts[best[i][2]] else ALLOW) if i in best else default for i in range(len(urls))]
    return [text(h) for h, _ in parts], [text(p) for _, p in parts], rules, verdicts


_OPEN: dict[str, DigestArray] = {}
#: Rule files that an application's workers have already.
_SENT: set[tuple[str, str]] = set()


def judge(df: DataFrame, rules: list[Rule], id_col: str = "page_id", url_col: str = "url", default: str = ALLOW) -> DataFrame:
    """One row per input row: id, host, path, rule, verdict.

    The longest fitting rule (host and path together, then the longer host)
    decides; without one the verdict is ``default``. Null, empty and malformed
    URLs have an empty host and path, which no rule fits. Repeated rows are
    judged one by one, an empty table gives an empty result, and only the two
    named columns are read, so further columns cannot clash.
    """
    spark = df.sparkSession
    ship(spark)
    # the name carries the content, so that other rules get another file
    stamp = xxhash.xxh64_hexdigest(repr(sorted((r.host, r.path, r.verdict) for r in rules)))
    name = f"url-rules-{stamp}.bin"
    sent = (spark.sparkContext.applicationId, name)
    if sent not in _SENT:
        local = os.path.join(tempfile.mkdtemp(prefix="pagecast-rules-"), name)
        DigestArray.write(rules, local)
        spark.sparkContext.addFile(local)
        _SENT.add(sent)
    id_type = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if name not in _OPEN:
            _OPEN[name] = DigestArray(SparkFiles.get(name))
        for batch in batches:
            host, path, rule, verdict = _judged(_OPEN[name], batch.column(1).to_pylist(), default)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(pa.array(x, pa.string()) for x in (host, path, rule, verdict))],
                [id_col, "host", "path", "rule", "verdict"],
            )

    return df.select(id_col, url_col).mapInArrow(run, f"{id_col} {id_type}, host string, path string, rule string, verdict string")


#: The rule list that the registered query applies (fixed values).
QUERY_RULES = [
    Rule("com", "/en/", BLOCK),
    Rule("example.com", "/en/7", ALLOW),
    Rule("net", "/de/", ALLOW),
    Rule("example.net", "/de/8", BLOCK),
    Rule("org", "/es/", BLOCK),
]

ORACLE = r"""
WITH cut AS (
  SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages
), parts AS (
  SELECT page_id, regexp_extract(rest, '^[^/?#]*') AS raw_host,
         regexp_extract(substr(rest, length(regexp_extract(rest, '^[^/?#]*')) + 1), '^[^?#]*') AS path FROM cut
), hosts AS (
  SELECT page_id, translate(raw_host, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, path FROM parts
), rules(rule_host, rule_path, rule_verdict) AS (
  VALUES ('com', '/en/', 'block'), ('example.com', '/en/7', 'allow'), ('net', '/de/', 'allow'),
         ('example.net', '/de/8', 'block'), ('org', '/es/', 'block')
), hits AS (
  SELECT page_id, arg_max(rule_host || rule_path, length(rule_host || rule_path) * 1000 + length(rule_host)) AS rule,
         arg_max(rule_verdict, length(rule_host || rule_path) * 1000 + length(rule_host)) AS verdict
  FROM hosts JOIN rules ON (host = rule_host OR suffix(host, '.' || rule_host)) AND prefix(path, rule_path)
  GROUP BY page_id
)
SELECT h.page_id, coalesce(h.host, '') AS host, coalesce(h.path, '') AS path, x.rule, coalesce(x.verdict, 'allow') AS verdict
FROM hosts h LEFT JOIN hits x USING (page_id)
"""
