"""Secrets in texts, judged by who else in the corpus holds the same value.

One scan finds candidates: credential assignments, access keys, long hex runs
and, beyond these, bare high-entropy tokens.  Candidate values leave the scan
as hashes only.  Two grouped counts over the corpus give, for each hash, its
distinct owners and repositories; a value that several owners hold is a widely
copied example, one that a single owner holds and that looks random is live.
Live bare tokens are added to the spans of their text.

Counts are pre-aggregated a task (distinct (hash, owner) first), and the join
back to the occurrences splits hot hashes; texts are never shuffled.

Defined cases: null text is empty; null owner or repository is an owner of its
own; repeated rows give equal rows; matches of equal start are listed assign,
access, hex, token; extra columns are ignored; an empty table gives an empty
result.
"""

from __future__ import annotations

import hashlib
import math
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import bounded, materialise

# The patterns of the base kinds.
ASSIGN = re.compile(r"((?:[Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy]))[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{32,}")  # a maximal run, as leftmost matching gives it
TOKEN = re.compile(r"[A-Za-z0-9+/_=-]{20,}")
KINDS = ("assign", "access", "hex", "token")


def entropy(value: str) -> float:
    """Bits a character."""
    n = len(value)
    return -sum(c / n * math.log2(c / n) for c in map(value.count, set(value)))


def looks_random(value: str) -> bool:
    return len(value) >= 8 and any(c.isdigit() for c in value) and any(c.isalpha() for c in value) and entropy(value) >= 2.8


def candidates(text: str) -> list[tuple[int, int, int, str]]:
    """(start, kind number, end, value) in order; bare tokens only where they
    overlap no base span."""
    out = []
    if ":" in text or "=" in text:
        out += [(m.start(), 0, m.end(), m[2]) for m in ASSIGN.finditer(text) if len(m[2]) >= 8]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end(), m[0]) for m in ACCESS.finditer(text) if len(m[0]) >= 16]
    out += [(m.start(), 2, m.end(), m[0]) for m in HEX.finditer(text)]
    out.sort()
    base, at, last = list(out), 0, 0
    for m in TOKEN.finditer(text):
        while at < len(base) and base[at][0] < m.end():
            last = max(last, base[at][2])
            at += 1
        if last <= m.start() and looks_random(m[0]):
            out.append((m.start(), 3, m.end(), m[0]))
    return sorted(out)


def _scan(batches):
    found = pa.list_(pa.struct([("start", pa.int32()), ("kind", pa.int32()), ("stop", pa.int32()), ("hash", pa.binary()), ("random", pa.bool_())]))
    for batch in batches:
        rows = []
        for text in batch.column(1):
            rows.append([{"start": a, "kind": k, "stop": b, "hash": hashlib.blake2b(v.encode(), digest_size=16).digest(), "random": looks_random(v)} for a, k, b, v in candidates(text.as_py() or "")])
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), batch.column(3), batch.column(4), pa.array(rows, found)], ["doc_id", "content", "owner", "repo", "found"])


def scan_candidates(docs: DataFrame, owner_col: str = "source", repo_col: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, content hash, owner, repo, found: candidates of each text."""
    repo = F.col(repo_col) if repo_col else F.concat_ws("/", F.col(owner_col), F.col("lang") if "lang" in docs.columns else F.lit(""))
    src = bounded(docs).select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"), F.xxhash64(F.col(text_col)).alias("content"), F.coalesce(F.col(owner_col).cast("string"), F.lit("")).alias("owner"), F.coalesce(repo.cast("string"), F.lit("")).alias("repo"))
    return src.mapInArrow(_scan, "doc_id bigint, content bigint, owner string, repo string, found array<struct<start:int,kind:int,stop:int,hash:binary,random:boolean>>")


def ownership(scan: DataFrame) -> DataFrame:
    """(hash, owners, repos, uses) of every candidate value."""
    one = scan.select("owner", "repo", F.explode("found.hash").alias("hash"))
    by_owner = one.groupBy("hash", "owner", "repo").agg(F.count("*").alias("uses"))
    by_owner = by_owner.groupBy("hash", "owner").agg(F.count("*").alias("repos"), F.sum("uses").alias("uses"))
    return by_owner.groupBy("hash").agg(F.count("*").alias("owners"), F.sum("repos").alias("repos"), F.sum("uses").alias("uses"))


def find_secrets(docs: DataFrame, max_owners: int = 1, **columns) -> DataFrame:
    """Per row of ``docs``: doc_id, spans (start, kind, stop, owners, repos,
    live) of all base candidates and of the live bare tokens, by start."""
    scan = materialise(scan_candidates(docs, **columns), "secrets")
    freq = ownership(scan)
    uses = scan.select("doc_id", "content", "owner", F.explode("found").alias("f")).select("doc_id", "content", "f.*")
    judged = uses.join(freq, "hash").withColumn("live", (F.col("owners") <= max_owners) & F.col("random")).where("kind < 3 or live")
    spans = judged.groupBy(F.col("doc_id").alias("_id"), F.col("content").alias("_content")).agg(F.sort_array(F.collect_set(F.struct("start", "kind", "stop", "owners", "repos", "live"))).alias("spans"))
    return scan.select("doc_id", "content").join(spans, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("content") == F.col("_content")), "left").select("doc_id", F.coalesce("spans", F.array().cast(spans.schema["spans"].dataType)).alias("spans"))


def secret_report(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_live."""
    name = F.array(*map(F.lit, KINDS))
    text = lambda x: F.concat_ws(":", F.element_at(name, x["kind"] + 1), x["start"].cast("string"), x["stop"].cast("string"))
    base = F.filter("spans", lambda x: x["kind"] < 3)
    count = lambda k: F.size(F.filter("spans", lambda x: x["kind"] == k)).cast("bigint")
    return find_secrets(docs, **options).select(
        "doc_id",
        count(0).alias("n_assign"),
        count(1).alias("n_access"),
        count(2).alias("n_hex"),
        F.sha2(F.array_join(F.transform(base, text), ","), 256).alias("base_sha256"),
        F.array_join(F.transform("spans", text), ",").alias("spans"),
        F.size(F.filter("spans", lambda x: x["live"])).cast("bigint").alias("n_live"),
    )
