"""URL rules in a memory-mapped, sorted array of 64-bit digests.

A rule is a host and a path prefix.  :func:`build_index` lays out one file: the
sorted XXH64 digests of the rules' strings, then the strings themselves.  Its
bytes (of a checked size) are broadcast; each worker puts them in an unnamed
file of its own, maps that once, and probes whole batches with a vectorised
binary search.  A hit counts only if the stored
string equals the probed one, so colliding digests never decide.

For each URL the probed strings are (host suffix at a label boundary) x (path
prefix of a length that some rule has); the longest rule found wins, of equally
long ones that with the longer host.  A URL that no rule fits is allowed.  A
list whose file would exceed ``MAX_INDEX_BYTES`` is dealt over several files
by host, each of them one more pass over the URLs.

Edge cases: a null URL, or one without ``://``, has an empty host and path and
fits no rule; repeated rows stay rows; extra columns are ignored; an empty
table gives an empty result.
"""

from __future__ import annotations

import tempfile
from functools import lru_cache
from typing import BinaryIO

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from delprop.llm.common import map_arrow

BLOCK, ALLOW = "block", "allow"
_NUL = "\x00"
#: Bytes of one file: every worker holds a copy on its disk.
MAX_INDEX_BYTES = 1 << 30


def host_of(url: Column) -> Column:
    rest = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1)
    return F.translate(rest, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def build_index(rules: list[tuple[str, str, str]]) -> bytes:
    """Lay out ``(verdict, host, path prefix)`` rules: counts, digests, offsets, lengths, blocked flags, prefix lengths, string bytes."""
    entries: dict[bytes, int] = {}
    for verdict, host, prefix in rules:
        text = (host + _NUL + prefix).encode()
        # of rules that name the same place, a block stands
        entries[text] = max(entries.get(text, 0), int(verdict == BLOCK))
    texts = sorted(entries, key=lambda t: (xxhash.xxh64_intdigest(t), t))
    digests = np.array([xxhash.xxh64_intdigest(t) for t in texts], np.uint64)
    lengths = np.array([len(t) for t in texts], np.int64)
    offsets = np.cumsum(lengths) - lengths
    flags = np.array([entries[t] for t in texts], np.int64)
    prefixes = np.unique(np.array([len(t.split(_NUL.encode(), 1)[1].decode()) for t in texts], np.int64))
    head = np.array([len(texts), len(prefixes)], np.int64)
    raw = b"".join([part.tobytes() for part in (head, digests, offsets, lengths, flags, prefixes)] + texts)
    return raw


def parts_of(rules: list[tuple[str, str, str]], most: int) -> list[list[tuple[str, str, str]]]:
    """The rules dealt by host over as many parts as keep a part's file near ``most`` bytes; one part at least."""
    size = sum(40 + len((h + p).encode()) for _, h, p in rules)
    count = -(-2 * size // most) if size > most else 1  # twice as many, since hosts are uneven
    parts: list[list[tuple[str, str, str]]] = [[] for _ in range(count)]
    for rule in rules:
        parts[xxhash.xxh64_intdigest(rule[1].encode()) % count].append(rule)
    return [p for p in parts if p] or [[]]


class Index:
    """Read-only view of a file that holds the bytes of :func:`build_index`."""

    def __init__(self, file: BinaryIO) -> None:
        raw = np.memmap(file, np.uint8, "r")
        n, k = raw[:16].view(np.int64).tolist()
        at = 16
        self.digests = raw[at : at + 8 * n].view(np.uint64)
        self.offsets, self.lengths, self.blocked = (raw[at + 8 * n * i : at + 8 * n * (i + 1)].view(np.int64) for i in (1, 2, 3))
        at += 32 * n
        self.prefixes = raw[at : at + 8 * k].view(np.int64).tolist()
        self.text = raw[at + 8 * k :]

    def find(self, probes: list[bytes]) -> np.ndarray:
        """Position of each probed string, or -1."""
        keys = np.fromiter(map(xxhash.xxh64_intdigest, probes), np.uint64, len(probes))
        low, high = np.searchsorted(self.digests, keys, "left"), np.searchsorted(self.digests, keys, "right")
        found = np.full(len(probes), -1, np.int64)
        for i in np.flatnonzero(low < high).tolist():
            for at in range(low[i], high[i]):
                a = self.offsets[at]
                if self.text[a : a + self.lengths[at]].tobytes() == probes[i]:
                    found[i] = at
        return found

    def judge(self, hosts: list[str], paths: list[str]) -> tuple[list[str | None], list[str], list[tuple[int, int]]]:
        """Winning rule, verdict and (length, host length) of the rule for each (host, path)."""
        probes, owner = [], []
        for row, (host, path) in enumerate(zip(hosts, paths, strict=True)):
            if not host:
                continue
            labels = host.split(".")
            for k in range(len(labels)):
                suffix = ".".join(labels[k:])
                for length in self.prefixes:
                    if length <= len(path):
                        probes.append((suffix + _NUL + path[:length]).encode())
                        owner.append(row)
        rules: list[str | None] = [None] * len(hosts)
        verdicts, ranks = [ALLOW] * len(hosts), [(0, 0)] * len(hosts)
        if probes:
            at = self.find(probes)
            for i in np.flatnonzero(at >= 0).tolist():
                rule_host, prefix = probes[i].decode().split(_NUL, 1)
                rank = (len(rule_host) + len(prefix), len(rule_host))
                if rules[owner[i]] is None or rank > ranks[owner[i]]:
                    rules[owner[i]], ranks[owner[i]] = rule_host + prefix, rank
                    verdicts[owner[i]] = BLOCK if self.blocked[at[i]] else ALLOW
        return rules, verdicts, ranks


@lru_cache(maxsize=2)
def _mapped(raw: bytes) -> Index:
    """The worker's map of a broadcast index; the file has no name, so it goes with the worker."""
    with tempfile.TemporaryFile() as file:
        file.write(raw)
        file.flush()
        return Index(file)


def judge_urls(pages: DataFrame, rules: list[tuple[str, str, str]], id_col: str = "page_id", url_col: str = "url", most: int = MAX_INDEX_BYTES) -> DataFrame:
    """(id, host, path, rule, verdict) for every row of ``pages``."""
    rows = pages.select(F.col(id_col), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    kind = dict(rows.dtypes)[id_col]
    schema = f"`{id_col}` {kind}, host string, path string, rule string, verdict string"
    parts = parts_of(rules, most)
    for part in parts:
        shipped = pages.sparkSession.sparkContext.broadcast(build_index(part))

        def kernel(batch: pa.RecordBatch, shipped=shipped) -> pa.RecordBatch:
            found, verdicts, ranks = _mapped(shipped.value).judge(batch.column("host").to_pylist(), batch.column("path").to_pylist())
            if "rank" in batch.schema.names:  # an earlier part's rule stays unless this one's ranks higher
                earlier = [tuple(r) for r in batch.column("rank").to_pylist()]
                keep = [old >= new for old, new in zip(earlier, ranks, strict=True)]
                found, verdicts, ranks = ([a if k else b for k, a, b in zip(keep, x, y, strict=True)] for x, y in ((batch.column("rule").to_pylist(), found), (batch.column("verdict").to_pylist(), verdicts), (earlier, ranks)))
            out = [batch.column(0), batch.column("host"), batch.column("path"), pa.array(found, pa.string()), pa.array(verdicts, pa.string()), pa.array([list(r) for r in ranks], pa.list_(pa.int32()))]
            return pa.record_batch(out, [batch.schema.names[0], "host", "path", "rule", "verdict", "rank"])

        rows = map_arrow(rows, kernel, schema + ", rank array<int>")
    return rows.drop("rank")
