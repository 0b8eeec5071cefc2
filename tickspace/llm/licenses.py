"""Known licences by the digest of a text's canonical form.

The canonical form lower-cases, drops copyright lines, unites equivalent
spellings, turns punctuation into blanks and squeezes these; its SHA-256 is the
join key.  No pattern reaches beyond a line, so a text's form is that of its
lines, joined by blanks, and is computed once.

Digests are looked up for the entire text and, with ``by_line``, for every run
of whole lines (a notice of one line, a wrapped one, a licence within a longer
text).  A run is digested where its form has the length and the first eight
bytes of some known form: all runs with a known digest have.  These pairs, one
a licence at most, go to the tasks; the join's licence side is the smaller one
by its statistics.

Defined cases: null or empty text, and texts that are nothing but copyright
lines and punctuation, have no digest and match nothing; licences of equal
canonical form are reported under the smallest name; repeated rows are reported
each; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from importlib import resources

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import bounded, materialise
from .textkernel import chunks

# Spellings held equal (as regular expressions), and one-line
# notices of common licences.
SPELLINGS = [("licence", "license"), ("sublicence", "sublicense"), ("organisation", "organization"), ("acknowledgement", "acknowledgment"), ("whilst", "while"), ("https?://", " ")]
NOTICES = [
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("MIT", "Released under the MIT License."),
    ("proprietary", "All rights reserved."),
    ("CC0-1.0", "This work is dedicated to the public domain under CC0 1.0."),
    ("BSD-3-Clause", "Licensed under the 3-clause BSD License."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
]
#: what stands above the short texts of ``license_texts``, or not
TITLES = {
    "MIT": ["MIT License", "The MIT License", "The MIT License (MIT)"],
    "BSD-2-Clause": ["BSD 2-Clause License", "Simplified BSD License", "All rights reserved.", "BSD 2-Clause License\nAll rights reserved."],
    "BSD-3-Clause": ["BSD 3-Clause License", "The BSD 3-Clause License", "All rights reserved.", "BSD 3-Clause License\nAll rights reserved."],
    "BSD-3-Clause-UC": ["All rights reserved."],
}
_COPYRIGHT = r"(?md)^[ \t]*(?:copyright|\(c\)|©)[^\n]*$"


def canonical(text: Column) -> Column:
    out = F.regexp_replace(F.lower(text), _COPYRIGHT, " ")
    for one, other in SPELLINGS:
        out = F.regexp_replace(out, one, other)
    return F.trim(F.regexp_replace(out, r"[^a-z0-9\x{80}-\x{10ffff}]+", " "))


def digest(text: Column) -> Column:
    """Null where the canonical form is empty."""
    form = canonical(text)
    return F.when(form != "", F.sha2(form, 256))


def notices(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(NOTICES, "license string, text string")


def whole_texts() -> list[tuple[str, str]]:
    """(license, text) of the files of ``license_texts``, titles being optional."""
    out = []
    for file in sorted(resources.files(__package__).joinpath("license_texts").iterdir(), key=lambda f: f.name):
        if file.name.endswith(".txt"):
            name, text = file.name[:-4], file.read_text(encoding="utf-8")
            out += [(name, text)] + [(name, f"{title}\n{text}") for title in TITLES.get(name, [])]
    return out


def known_licenses(spark: SparkSession) -> DataFrame:
    """The notices and the whole texts."""
    return spark.createDataFrame(NOTICES + whole_texts(), "license string, text string")


def _line_runs(known_b):
    def run(batches):
        known = {n: np.array(sorted(heads), np.uint64) for n, heads in known_b.value.items()}
        for batch in batches:
            found = [None] * batch.num_rows
            for row, end, data, off in chunks(batch.column(2)):
                if not len(data):
                    continue
                n = len(data)
                opens = np.zeros(n + 1, bool)
                opens[off], opens[n] = True, False
                breaks = np.flatnonzero(data == 10)
                opens[breaks + 1] = True
                closes = np.zeros(n + 1, bool)
                closes[off], closes[breaks] = True, True
                start = np.flatnonzero(opens)
                padded = np.append(data, np.zeros(8, np.uint8))
                head = np.ascontiguousarray(padded[start[:, None] + np.arange(8)]).view("<u8")[:, 0]
                text = np.searchsorted(off, start, "right") - 1
                for size, heads in known.items():
                    some = np.isin(head, heads) if size >= 8 else np.ones(len(start), bool)
                    at, of = start[some], text[some]
                    ok = at + size <= off[of + 1]
                    at, of = at[ok], of[ok]
                    ok = closes[at + size]
                    for i, t in zip(at[ok], of[ok]):
                        sha = hashlib.sha256(data[i : i + size].tobytes().replace(b"\n", b" ")).hexdigest()
                        found[row + t] = [*(found[row + t] or ()), sha]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(found, pa.list_(pa.string())), batch.column(3)], ["doc_id", "digest", "parts", "uid"])

    return run


def license_matches(docs: DataFrame, licenses: DataFrame, by_line: bool = True, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a row of ``docs``: doc_id, digest of the entire text, license
    (entire text), line_licenses (sorted names of licences that runs of whole
    lines are)."""
    named = licenses.select(canonical(F.col("text")).alias("form"), "license").where("form <> ''")
    known = named.groupBy(F.sha2("form", 256).alias("known")).agg(F.min("license").alias("license"))
    src = bounded(docs).select(F.col(id_col).cast("bigint").alias("doc_id"), F.filter(F.transform(F.split(F.col(text_col), "\n"), canonical), lambda x: x != "").alias("forms"))
    form = F.array_join("forms", " ")
    src = src.select("doc_id", F.when(form != "", F.sha2(form, 256)).alias("digest"), F.array_join("forms", "\n").alias("lines"), F.monotonically_increasing_id().alias("uid"))
    pairs = {}
    if by_line:
        for r in named.select(F.octet_length("form").alias("n"), F.substring(F.encode("form", "utf-8"), 1, 8).alias("head")).distinct().collect():
            pairs.setdefault(r.n, set()).add(int.from_bytes(bytes(r.head)[:8], "little"))
    rows = src.select("doc_id", "digest", "lines", "uid").mapInArrow(_line_runs(docs.sparkSession.sparkContext.broadcast(pairs)), "doc_id bigint, digest string, parts array<string>, uid bigint")
    rows = materialise(rows, "digests")
    parts = rows.select("uid", F.explode("parts").alias("known")).join(known, "known").groupBy("uid").agg(F.sort_array(F.collect_set("license")).alias("line_licenses"))
    # rows without a digest get keys of their own, lest they meet in one task
    keyed = rows.withColumn("known", F.coalesce("digest", F.concat(F.lit("-"), F.col("uid").cast("string"))))
    return keyed.join(known, "known", "left").join(parts, "uid", "left").select("doc_id", "digest", "license", F.coalesce("line_licenses", F.array().cast("array<string>")).alias("line_licenses"))
