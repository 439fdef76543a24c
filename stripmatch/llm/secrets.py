"""Secret scans: base patterns, further candidates, and their ownership over the whole corpus.

Each candidate's value is hashed; over all documents the distinct owners and repositories of a hash are counted. A
value that few owners and few repositories hold looks live; any other is a widely copied example: an owner may keep
its own credential in two repositories, but what stands in five is a sample even if one owner has them all. Base spans
stay whatever their verdict; further candidates (long mixed tokens, bearer values, signed web tokens, private-key
blocks) become spans only if they look live and touch no base span.

Defined cases: null or empty text has no spans; a null owner or repository counts as one owner or repository of its
own; equal values in one document count once for it; repeated rows are reported each; ties (spans that start
together) stand in the order of KINDS; extra columns are dropped, and kept by `masked` whatever their names; an empty
table gives no rows.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator
from math import log2

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stripmatch.cluster import ship, written
from stripmatch.llm import store
from stripmatch.llm.textnp import Chunk, U, chunks, mix

KINDS = ["assign", "access", "hex", "private", "web", "bearer", "mixed"]  # in the order of ties
BASE = 3
FEW_OWNERS, FEW_REPOSITORIES = 2, 4
# The base patterns.
ASSIGN = re.compile(rb"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.I)
ACCESS = re.compile(rb"AKIA[A-Z0-9]+")
_HINTS = (b"passw", b"secret", b"token", b"api")
_HEX = np.isin(np.arange(256), list(b"0123456789abcdef"))
_BEGIN = re.compile(rb"-----BEGIN [A-Z ]*PRIVATE KEY-----")
_END = re.compile(rb"-----END [A-Z ]*PRIVATE KEY-----")
# Tried once in a run of its letters, at the run's first eyJ: later ones end at the same dot. So long runs cost one walk.
_WEB = re.compile(rb"(?<![A-Za-z0-9_-])(?>[A-Za-z0-9_-]*?(?=eyJ))(eyJ[A-Za-z0-9_-]{8,}+\.[A-Za-z0-9_-]{8,}+\.[A-Za-z0-9_-]{8,}+)")
_BEARER = re.compile(rb"bearer\x20+([A-Za-z0-9._~+/=-]{16,})", re.I)
_MIXED = re.compile(rb"[A-Za-z0-9+/_-]{20,}={0,2}")
Span = tuple[int, int, int, bytes]  # start, kind, end (bytes of the text), value


def base_spans(raw: bytes, hex_runs: list[tuple[int, int]]) -> list[Span]:
    found = [(s, 2, e, raw[s:e]) for s, e in hex_runs]
    low = raw.lower()
    if any(h in low for h in _HINTS):
        found += [(m.start(), 0, m.end(), m[2]) for m in ASSIGN.finditer(raw) if len(m[2]) >= 12]
    if b"AKIA" in raw:
        found += [(m.start(), 1, m.end(), m[0]) for m in ACCESS.finditer(raw) if len(m[0]) >= 18]
    return sorted(found)


def entropy(value: bytes) -> float:
    return -sum(n / len(value) * log2(n / len(value)) for n in Counter(value).values()) if value else 0.0


def private_spans(raw: bytes) -> list[Span]:
    """From each BEGIN line to the nearest END line after it, of any length, in one walk over the text."""
    found, at = [], 0
    while begin := _BEGIN.search(raw, at):
        end = _END.search(raw, begin.end())
        if not end:
            break
        at = end.end()
        found.append((begin.start(), 3, at, raw[begin.start() : at]))
    return found


def further_spans(raw: bytes, words: list[tuple[int, int]], base: list[Span]) -> list[Span]:
    """words: the long words, where mixed tokens can be."""
    found: list[Span] = []
    if b"PRIVATE KEY-----" in raw:
        found += private_spans(raw)
    if b"eyJ" in raw:
        found += [(m.start(1), 4, m.end(1), m[1]) for m in _WEB.finditer(raw)]
    if b"earer" in raw or b"EARER" in raw:
        found += [(m.start(1), 5, m.end(1), m[1]) for m in _BEARER.finditer(raw)]
    for s, e in words:
        for m in _MIXED.finditer(raw, s, e):
            v = m[0]
            if re.search(rb"[0-9]", v) and re.search(rb"[a-z]", v) and re.search(rb"[A-Z]", v) and entropy(v) >= 3.5:
                found.append((m.start(), 6, m.end(), v))
    starts, ends = [], []  # what base spans cover, as disjoint stretches
    for s, _, e, _ in base:
        if ends and s <= ends[-1]:
            ends[-1] = max(ends[-1], e)
        else:
            starts.append(s), ends.append(e)
    out, end = [], 0
    for span in sorted(found):
        i = bisect_left(starts, span[2]) - 1  # the last stretch that begins before the span ends
        if span[0] >= end and (i < 0 or ends[i] <= span[0]):
            out.append(span)
            end = span[2]
    return out


def points(raw: bytes, spans: list[Span]) -> list[tuple[int, int, int, str]]:
    """Spans by code points, with their values' hashes."""
    if not spans:
        return []
    if raw.isascii():
        at = {x: x for s, _, e, _ in spans for x in (s, e)}
    else:
        lead = np.cumsum((np.frombuffer(raw, np.uint8) & 0xC0) != 0x80)
        at = {x: int(lead[x - 1]) if x else 0 for s, _, e, _ in spans for x in (s, e)}
    return [(at[s], k, at[e], hashlib.sha256(v).hexdigest()[:32]) for s, k, e, v in spans]


_SPAN = pa.struct([("start", pa.int32()), ("rank", pa.int32()), ("end", pa.int32()), ("value", pa.string())])


def spans_of(c: Chunk) -> Iterator[tuple[bytes, list[Span], list[Span]]]:
    """(text, base spans, further candidates) of a chunk's texts."""
    raw = c.b.tobytes()
    runs: dict[int, list] = {}
    if len(c.b):
        h = np.concatenate([[False], _HEX[c.b], [False]])
        s, e = np.flatnonzero(~h[:-1] & h[1:]), np.flatnonzero(h[:-1] & ~h[1:])
        long_run = e - s >= 16  # a run over a text's end is cut there
        for s, e in zip(s[long_run].tolist(), e[long_run].tolist()):
            d = int(np.searchsorted(c.off, s, "right")) - 1
            while s < e:
                stop = min(e, int(c.off[d + 1]))
                if stop - s >= 16:
                    runs.setdefault(d, []).append((s - int(c.off[d]), stop - int(c.off[d])))
                s, d = stop, d + 1
    words: dict[int, list] = {}
    for i in np.flatnonzero(c.we - c.ws >= 20).tolist():
        d = int(c.wd[i])
        words.setdefault(d, []).append((int(c.ws[i] - c.off[d]), int(c.we[i] - c.off[d])))
    for d in range(c.n):
        text = raw[int(c.off[d]) : int(c.off[d + 1])]
        base = base_spans(text, runs.get(d, []))
        yield text, base, further_spans(text, words.get(d, []), base)


def scan(docs: DataFrame, owner: Column, repository: Column) -> DataFrame:
    """One row per document: row (its number), doc_id, owner, repository, digest (of its text), base and further spans. Nothing is judged yet."""
    ship(docs.sparkSession)
    narrow = docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", F.coalesce(owner.cast("string"), F.lit("\0")).alias("owner"), F.coalesce(repository.cast("string"), F.lit("\0")).alias("repository"), F.xxhash64("text").alias("digest"), "text")

    def run(batches):
        for batch in batches:
            for c in chunks(batch.column(5)):
                found = [(points(t, b), points(t, f)) for t, b, f in spans_of(c)]
                base, further = ([[dict(zip(("start", "rank", "end", "value"), x)) for x in f[i]] for f in found] for i in (0, 1))
                kept = [batch.column(j).slice(c.lo, c.n) for j in range(5)]
                yield pa.RecordBatch.from_arrays([*kept, pa.array(base, pa.list_(_SPAN)), pa.array(further, pa.list_(_SPAN))], ["row", "doc_id", "owner", "repository", "digest", "base", "further"])

    span = "array<struct<start:int,rank:int,end:int,value:string>>"
    return narrow.mapInArrow(run, f"row long, doc_id {dict(narrow.dtypes)['doc_id']}, owner string, repository string, digest long, base {span}, further {span}")


def ownership(scanned: DataFrame) -> DataFrame:
    """value, owners, repositories: over the whole corpus. Distinct holders first, so a hot value is summed, not gathered."""
    held = scanned.select("owner", "repository", F.explode(F.array_distinct(F.transform(F.concat("base", "further"), lambda x: x["value"]))).alias("value"))
    return holders(held)


def holders(held: DataFrame) -> DataFrame:
    """owners, repositories and documents of each value. held: owner, repository, value, a row per document and value."""
    pairs = held.groupBy("value", "owner", "repository").agg(F.count(F.lit(1)).alias("documents"))
    repos = pairs.groupBy("value", "owner").agg(F.count(F.lit(1)).alias("repositories"), F.sum("documents").alias("documents"))
    return repos.groupBy("value").agg(F.count(F.lit(1)).alias("owners"), F.sum("repositories").alias("repositories"), F.sum("documents").alias("documents"))


def looks_live(owners: int, repositories: int) -> Column:
    return (F.col("owners") <= owners) & (F.col("repositories") <= repositories)


def find_secrets(docs: DataFrame, owner: Column, repository: Column, owners: int = FEW_OWNERS, repositories: int = FEW_REPOSITORIES) -> tuple[DataFrame, DataFrame]:
    """(documents, spans): documents have row, doc_id, digest, base, spans (all, judged), n_live, n_example; spans have doc_id, kind, start, end, owners, repositories, verdict."""
    scanned = written(scan(docs, owner, repository), "secrets")
    counts = ownership(scanned)
    cands = scanned.select("row", "doc_id", F.explode(F.concat("base", "further")).alias("s")).select("row", "doc_id", "s.*")
    judged = cands.join(counts, "value").withColumn("live", looks_live(owners, repositories))
    further = F.collect_list(F.when(F.col("live") & (F.col("rank") >= BASE), F.struct("start", "rank", "end", "value"))).alias("added")
    told = judged.groupBy("row").agg(further, F.count_if("live").alias("n_live"), F.count_if(~F.col("live")).alias("n_example"))
    every = F.array_sort(F.concat("base", F.coalesce("added", F.filter("base", lambda x: F.lit(False)))))
    counted = [F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("n_live", "n_example")]
    full = scanned.join(told, "row", "left").select("row", "doc_id", "digest", "base", every.alias("spans"), *counted)
    kinds = F.array(*map(F.lit, KINDS))
    spans = judged.select("doc_id", F.element_at(kinds, F.col("rank") + 1).alias("kind"), "start", "end", "value", "owners", "repositories", F.when(F.col("live"), "live").otherwise("example").alias("verdict"))
    return full, spans


def joined_spans(spans: Column) -> Column:
    kinds = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.element_at(kinds, x["rank"] + 1), x["start"], x["end"])), ",")


def value_key(value: bytes) -> int:
    return int.from_bytes(hashlib.sha256(value).digest()[:8], "little", signed=True)


def masked(docs: DataFrame, owner: Column, repository: Column, mask: str = "[secret]", owners: int = FEW_OWNERS, repositories: int = FEW_REPOSITORIES) -> DataFrame:
    """docs with every base span, and every further candidate that looks live, replaced in its text; all columns are kept.

    Two passes over the texts, neither of which shuffles one: the first sends the further candidates' hashes to be
    counted, the second masks by a store of those that look live. Overlapping spans are masked as one.
    """
    spark = docs.sparkSession
    ship(spark)
    bits, live = store.range_bits(spark), store.new_folder(spark, "secrets-live")
    at = docs.columns.index("text")
    named = lambda c: F.coalesce(c.cast("string"), F.lit("\0"))

    def candidates(batches):
        for batch in batches:
            for c in chunks(batch.column(2)):
                rows = [(c.lo + i, v) for i, (_, _, further) in enumerate(spans_of(c)) for v in {value_key(x[3]) for x in further}]
                own = pa.array([i for i, _ in rows], pa.int64())
                yield pa.RecordBatch.from_arrays([batch.column(0).take(own), batch.column(1).take(own), pa.array([v for _, v in rows], pa.int64())], ["owner", "repository", "value"])

    held = docs.select(named(owner).alias("owner"), named(repository).alias("repository"), "text").mapInArrow(candidates, "owner string, repository string, value long")
    store.write_lookup(holders(held).where(looks_live(owners, repositories)).select("value"), bits, live)

    def run(batches):
        known = store.Store(live, bits)
        for batch in batches:
            texts = []
            for c in chunks(batch.column(at)):
                found = list(spans_of(c))
                keys = [value_key(x[3]) for _, _, further in found for x in further]
                ok = iter(known.find(mix(np.array(keys, np.int64).view(U)))[0].tolist())
                for text, base, further in found:
                    cut, out, end = sorted(base + [x for x in further if next(ok)]), [], 0
                    for s, _, e, _ in cut:
                        if s >= end:
                            out += [text[end:s], mask.encode()]
                        end = max(end, e)
                    texts.append(b"".join([*out, text[end:]]).decode())
            new = pa.array(texts, pa.string())
            new = pc.if_else(batch.column(at).is_null(), pa.scalar(None, pa.string()), new)
            yield pa.RecordBatch.from_arrays([new.cast(f.type) if i == at else batch.column(i) for i, f in enumerate(batch.schema)], schema=batch.schema)

    return docs.mapInArrow(run, docs.schema)
