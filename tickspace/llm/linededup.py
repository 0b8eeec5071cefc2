"""Recurring lines across documents, found by a fixed-depth log-template tree.

A text's records are its lines, long lines being cut after sentence ends (a
passage copied into the middle of a line is then a run of records too).  The
tree has fixed depth: token count, then the ``DEPTH`` leading tokens, then a leaf.
Tokens that hold a digit are variable fields and generalise to one wildcard at
every level, in records of which they are at most half (rows of numbers are not
one template, but compared as they are).  A record's templates are its path and,
below the leaf,

* all further tokens;
* for whole lines of at least ``merge_tokens`` tokens, a quarter of the further
  ones at most with digits, besides, one half of the further tokens (the first, the second, those at even or those at odd places):
  records of one leaf that agree in such a half are one template, in which the
  places of the other half where they differ are wildcards.  They agree in more
  than half of their places, whatever fills the rest.

A path is hashed into one key, so a template is one group of a distributed
aggregation and no task walks the tree, or holds a leaf, alone.

A template recurs when at least ``min_docs`` documents have it (``short_docs``
where it has fewer than ``long_tokens`` tokens, ``merge_docs`` where it has
wildcards for tokens without digits; records of fewer than
``min_tokens`` tokens never do alone).  The document with the smallest id keeps
its records of the template, all other documents lose theirs.

Two rules more find passages whatever the borders of their records:

* a record of fewer than ``long_tokens`` tokens is also judged together with the
  records after it, and with those before it, that bring it to that length;
  such a group is one long record, and all its records go with it;
* every run of ``run_tokens`` words of which the records leave any, wherever it
  begins and ends, stays in the document of the smallest id that has it and is
  cut from all others, so a longer shared passage goes whole.  The smallest k-gram hash of a run marks it:
  runs are compared only where two documents share the mark, which equal runs do.

Characters of scripts without blanks are tokens of their own.  n_dropped counts
records of which no word is left.  A cut from within a line to its end keeps the
line break.

Shuffles: a few numbers a record, group and mark, written once and pre-aggregated
a task for the counts; the joins back split hot templates; texts move once to
meet their shared marks, which only some have, and once to meet what they lose.

Defined cases: null text stays null, empty text stays empty; repeated rows
under one id count as documents of their own and share their fate; a null id
sorts last (it keeps a template only if no other document has it); columns
beyond id and text, whatever their names, pass through; an empty table gives
an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import bounded, materialise, remove, shared_dir
from .textkernel import BLANKS, U, Words, chunks, mix, script_cuts, span, sums, words

DEPTH = 2  #: leading tokens that are levels of the tree of their own
_STOPS = np.zeros(256, bool)
_STOPS[[33, 46, 63]] = True
_DIGIT = np.zeros(256, np.int32)
_DIGIT[48:58] = 1
_WILD = U(0x2A2A2A2A2A2A2A2A)


@dataclass
class Records:
    """Of every record: text row, number within the text, first word, end word,
    key of the leaf, whether it may be merged; and the words, the tokens
    (wildcards for those with digits) and their sums."""

    text: np.ndarray
    number: np.ndarray
    first: np.ndarray
    last: np.ndarray
    leaf: np.ndarray
    line: np.ndarray
    words: Words
    tokens: np.ndarray
    sums: tuple

    def keys(self) -> np.ndarray:
        """Templates of all tokens."""
        return mix(self.leaf ^ span(self.sums, self.first, self.last, 20), 21)

    def merged(self, merge_tokens: int) -> tuple[np.ndarray, np.ndarray]:
        """(record, key) of the templates of half the tokens below the leaf."""
        some = np.flatnonzero(self.line & (self.last - self.first >= max(merge_tokens, DEPTH + 2)))
        if not len(some):
            return some, np.zeros(0, U)
        below, last, leaf = self.first[some] + DEPTH, self.last[some], self.leaf[some]
        middle = below + (last - below + 1) // 2
        at = np.arange(len(self.tokens)) % 2
        by = [sums(np.where(at == x, self.tokens, U(0)), self.sums) for x in (0, 1)]
        parity = [span(x, below, last, 25) for x in by]
        turned = below % 2 == 1
        halves = [span(self.sums, below, middle, 26), span(self.sums, middle, last, 27), np.where(turned, parity[1], parity[0]), np.where(turned, parity[0], parity[1])]
        return np.tile(some, 4), np.concatenate([mix(leaf ^ mix(h, 28 + i), 40) for i, h in enumerate(halves)])


def _layout(data: np.ndarray, off: np.ndarray, hashed: bool) -> tuple[Words, np.ndarray, np.ndarray]:
    """Words, those that open a line, those that open a record."""
    w = words(data, off, BLANKS, cuts=script_cuts(data), hashed=hashed)
    breaks = np.zeros(len(data) + 1, np.int32)
    np.cumsum(data == 10, out=breaks[1:])
    lines = np.ones(len(w.start), bool)
    lines[1:] = (w.text[1:] != w.text[:-1]) | (breaks[w.start[1:]] > breaks[w.end[:-1]])
    opens = lines.copy()
    opens[1:] |= _STOPS[data[w.end[:-1] - 1]]
    return w, lines, opens


@dataclass
class Places:
    """Where the records of all texts lie: text row, first word, end word; and
    the words, without their hashes."""

    text: np.ndarray
    first: np.ndarray
    last: np.ndarray
    words: Words


def places(data: np.ndarray, off: np.ndarray) -> Places:
    w, _, opens = _layout(data, off, False)
    first = np.flatnonzero(opens)
    return Places(w.text[first], first, np.append(first[1:], len(opens))[: len(first)], w)


def records(data: np.ndarray, off: np.ndarray) -> Records:
    w, lines, opens = _layout(data, off, True)
    m = len(w.start)
    if not m:
        z = np.zeros(0, np.int64)
        return Records(z, z, z, z, np.zeros(0, U), z.astype(bool), w, np.zeros(0, U), sums(np.zeros(0, U)))
    digits = np.zeros(len(data) + 1, np.int32)
    np.cumsum(_DIGIT[data], out=digits[1:])
    field = digits[w.end] > digits[w.start]
    first = np.flatnonzero(opens)
    last = np.append(first[1:], m)
    count = last - first
    fields = np.add.reduceat(field.astype(np.int64), first)
    tokens = np.where(field & np.repeat(2 * fields <= count, count), _WILD, w.hash)
    line = lines[first] & np.append(lines[last[:-1]], True) & (4 * fields <= count - DEPTH)
    key = mix(count.astype(U), 11)  # level 1: token count
    for d in range(DEPTH):  # next levels: leading tokens
        key = mix(key ^ np.where(count > d, tokens[np.minimum(first + d, m - 1)], U(0)), 12 + d)
    text = w.text[first]
    number = np.arange(len(first)) - np.searchsorted(text, text)
    return Records(text, number, first, last, key, line, w, tokens, sums(tokens))


def _groups(r: Records, long_tokens: int) -> tuple[np.ndarray, np.ndarray]:
    """(first record, last record) of the groups that bring each short record
    to ``long_tokens`` tokens, to the right and to the left."""
    short = np.flatnonzero(r.last - r.first < long_tokens)
    right = np.searchsorted(r.last, r.first[short] + long_tokens)
    left = np.searchsorted(r.first, r.last[short] - long_tokens, "right") - 1
    n = len(r.text)
    to = (right < n) & (r.text[np.minimum(right, n - 1)] == r.text[short])
    fro = (left >= 0) & (r.text[np.maximum(left, 0)] == r.text[short])
    pairs = np.unique(np.concatenate([short[to] * n + right[to], left[fro] * n + short[fro]]))
    return pairs // max(n, 1), pairs % max(n, 1)


def _marks(w: Words, run_tokens: int) -> tuple[np.ndarray, np.ndarray, tuple]:
    """(first word, mark) of every run of ``run_tokens`` words of one text, and
    the words' sums; the mark is the smallest hash of the run's k-grams."""
    k = max(1, run_tokens // 3)
    of = sums(w.hash)
    n = len(w.hash) - run_tokens + 1
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, U), of
    at = np.arange(len(w.hash) - k + 1)
    low, wide, width = span(of, at, at + k, 31), 1, run_tokens - k + 1
    while wide < width:
        step = min(wide, width - wide)
        low = np.minimum(low[:-step], low[step:])
        wide += step
    inside = np.flatnonzero(w.text[:n] == w.text[run_tokens - 1 :])
    return inside, low[inside], of


@dataclass(frozen=True)
class Needs:
    """What makes a template recur."""

    min_docs: int = 2
    min_tokens: int = 3
    long_tokens: int = 8
    short_docs: int = 5
    merge_docs: int = 3
    merge_tokens: int = 7
    run_tokens: int = 50


def _emit(needs: Needs):
    def run(batches):
        for batch in batches:
            ids, hashes = batch.column(0), np.asarray(batch.column(1))
            for row, end, data, off in chunks(batch.column(2)):
                r = records(data, off)
                count = r.last - r.first
                ok = np.flatnonzero(count >= needs.min_tokens)
                a, b = _groups(r, needs.long_tokens)
                half, half_key = r.merged(needs.merge_tokens)
                at, mark, _ = _marks(r.words, needs.run_tokens)
                new = np.ones(len(at), bool)
                new[1:] = (mark[1:] != mark[:-1]) | (r.words.text[at[1:]] != r.words.text[at[:-1]])
                at, mark = at[new], mix(mark[new], 32)
                group = mix(span(r.sums, r.first[a], r.last[b], 22) ^ mix((r.last[b] - r.first[a]).astype(U), 23), 24)
                text = np.concatenate([r.text[ok], r.text[a], r.text[half], r.words.text[at]])
                number = np.concatenate([r.number[ok], r.number[a], r.number[half], np.zeros(len(at), np.int64)])
                upto = np.concatenate([r.number[ok], r.number[b], r.number[half], np.full(len(at), -1)])
                need = np.concatenate([np.where(count[ok] < needs.long_tokens, needs.short_docs, needs.min_docs), np.full(len(a), needs.min_docs), np.full(len(half), needs.merge_docs), np.full(len(at), needs.min_docs)])
                key = np.concatenate([r.keys()[ok], group, half_key, mark])
                once = np.zeros(len(key), bool)  # a document counts once for a template
                once[np.unique(mix(key ^ mix(text.astype(U), 44), 45), return_index=True)[1]] = True
                some = once | (upto >= 0)
                text, number, upto, need, key, once = (c[some] for c in (text, number, upto, need, key, once))
                cols = [pa.array(number.astype(np.int32)), pa.array(upto.astype(np.int32)), pa.array(need.astype(np.int32)), pa.array(key.view(np.int64)), pa.array(once.astype(np.int32))]
                yield pa.RecordBatch.from_arrays([ids.take(pa.array(text + row)), pa.array(hashes[text + row]), *cols], ["id", "content", "number", "upto", "need", "template", "once"])

    return run


def _content(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return bounded(docs).select(F.col(id_col).cast("bigint").alias("id"), F.xxhash64(F.col(text_col)).alias("content"), F.col(text_col).alias("text"))


def template_records(docs: DataFrame, needs: Needs = Needs(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a record's template, a group of records and a mark: id, content
    hash, first and last record (-1: a mark), documents that make it recur, key,
    and whether it is the text's first of its key."""
    return _content(docs, id_col, text_col).mapInArrow(_emit(needs), "id bigint, content bigint, number int, upto int, need int, template bigint, once int")


def recurring(recs: DataFrame) -> DataFrame:
    """(template, keeper): templates that enough documents have and the
    smallest id among them."""
    return recs.groupBy("template").agg(F.sum("once").alias("docs"), F.min("id").alias("keeper"), F.max("need").alias("need")).where("docs >= need").select("template", "keeper")


def _flat(lists: pa.ListArray, row: int, end: int) -> tuple[np.ndarray, slice]:
    """Of the values of the lists row..end - 1: the list of each, and where they lie."""
    off = lists.offsets.to_numpy()[row : end + 1]
    return np.repeat(np.arange(end - row), np.diff(off)), slice(off[0], off[-1])


def _lost(r: Records | Places, drops: pa.ListArray, row: int, end: int) -> np.ndarray:
    """Steps at the words, whose running sum is above zero where a dropped
    record lies; ``drops``: of each text, first and last record."""
    text, mine = _flat(drops, row, end)
    base, size = np.searchsorted(r.text, np.arange(end - row))[text], len(r.words.start) + 1
    a, b = (drops.values.field(c).to_numpy()[mine] + base for c in ("a", "b"))
    return np.bincount(r.first[a], minlength=size) - np.bincount(r.last[b], minlength=size)


def _runs(run_tokens: int):
    owned = lambda mark, text: mix(mark ^ mix(text.astype(U), 46), 47)

    def run(batches):
        for batch in batches:
            shared, drops = batch.column(4), batch.column(5)
            for row, end, data, off in chunks(batch.column(3)):
                r = records(data, off)
                w, first = r.words, r.words.first(end - row)
                at, mark, of = _marks(w, run_tokens)
                text = w.text[at]
                new = np.ones(len(at), bool)
                new[1:] = (mark[1:] != mark[:-1]) | (text[1:] != text[:-1])
                holder, mine = _flat(shared, row, end)
                hit = np.isin(owned(mix(mark[new], 32), text[new]), owned(shared.values.to_numpy()[mine].view(U), holder))[np.cumsum(new) - 1]
                left = np.append(0, np.cumsum(np.cumsum(_lost(r, drops, row, end)[:-1]) == 0))
                hit &= left[at + run_tokens] > left[at]  # not where all words are gone already
                at, text = at[hit], text[hit]
                key, mine = span(of, at, at + run_tokens, 33), pa.array(text + row)
                yield pa.RecordBatch.from_arrays([*(batch.column(i).take(mine) for i in range(3)), pa.array(key.view(np.int64)), pa.array((at - first[text]).astype(np.int32))], ["uid", "id", "content", "run", "at"])

    return run


def _rebuild(at_text: int, n_columns: int, run_tokens: int):
    def run(batches):
        for batch in batches:
            old, out, lost, had = batch.column(at_text), [], [], []
            drops, cuts = (batch.column(n_columns + i) for i in range(2))
            for row, end, data, off in chunks(old):
                r = places(data, off)
                w, first = r.words, r.words.first(end - row)
                step = _lost(r, drops, row, end)
                text, mine = _flat(cuts, row, end)
                begin = cuts.values.to_numpy()[mine] + first[text]
                step += np.bincount(begin, minlength=len(step)) - np.bincount(begin + run_tokens, minlength=len(step))
                keep = np.cumsum(step[:-1]) == 0
                kept = np.append(0, np.cumsum(keep))
                had.append(np.bincount(r.text, minlength=end - row))
                lost.append(np.bincount(r.text[kept[r.last] == kept[r.first]], minlength=end - row))
                whole = np.diff(kept[first]) == np.diff(first)
                for i in range(end - row):
                    if whole[i]:
                        out.append(old[row + i].as_py())
                        continue
                    lo, hi = first[i], first[i + 1]
                    edge = np.flatnonzero(np.diff(np.concatenate([[False], keep[lo:hi], [False]]).astype(np.int8)))
                    stop = np.append(w.start[lo + 1 : hi], off[i + 1])  # of each word with what follows it
                    pieces = []
                    for a, b in edge.reshape(-1, 2):
                        begin = off[i] if a == 0 else w.start[lo + a]
                        if pieces and b"\n" not in pieces[-1][len(pieces[-1].rstrip(b" \t\n\r\x0b\x0c")) :] and b"\n" in data[w.end[lo + a - 1] : begin].tobytes():
                            pieces.append(b"\n")
                        pieces.append(data[begin : stop[b - 1]].tobytes())
                    out.append(b"".join(pieces).rstrip(b" \t\n\r\x0b\x0c").decode())
            had, lost = (np.concatenate([np.zeros(0, np.int64), *x]).astype(np.int32) for x in (had, lost))
            cols = [pa.array(out, pa.string()) if i == at_text else c for i, c in enumerate(batch.columns[:n_columns])]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(had), pa.array(lost)], schema=None, names=[f"c{i}" for i in range(len(cols) + 2)])

    return run


def drop_recurring_lines(docs: DataFrame, needs: Needs = Needs(), id_col: str = "doc_id", text_col: str = "text", counts: bool = False, drop_emptied: bool = False) -> DataFrame:
    """``docs`` with recurring records and runs cut out of the text; with
    ``counts`` also n_records and n_dropped; with ``drop_emptied`` without the
    rows that had words and have lost them all."""
    base = shared_dir(docs.sparkSession)
    recs = materialise(template_records(docs, needs, id_col, text_col), "records", base)
    rec = materialise(recurring(recs), "recurring", base)
    mark = F.col("upto") < 0
    hits = recs.join(rec, "template").where(mark | ~F.col("id").eqNullSafe(F.col("keeper")))
    drop = F.collect_set(F.when(~mark, F.struct(F.col("number").alias("a"), F.col("upto").alias("b")))).alias("_drop")
    drops = materialise(hits.groupBy(F.col("id").alias("_id"), F.col("content").alias("_content")).agg(drop, F.collect_set(F.when(mark, F.col("template"))).alias("_marks")), "drops", base)
    remove(docs.sparkSession, f"{base}/records")
    # runs of the texts with shared marks
    marks = drops.where(F.size("_marks") > 0)
    mine = lambda i, c: i.eqNullSafe(F.col("_id")) & (c == F.col("_content"))
    some = _content(docs, id_col, text_col).join(marks, mine(F.col("id"), F.col("content"))).select(F.monotonically_increasing_id().alias("uid"), "id", "content", "text", "_marks", "_drop")
    runs = materialise(some.mapInArrow(_runs(needs.run_tokens), "uid bigint, id bigint, content bigint, run bigint, at int"), "runs", base)
    shared = materialise(runs.groupBy("run").agg(F.min("id").alias("keeper"), (F.count("*") if needs.min_docs <= 2 else F.countDistinct("uid")).alias("n")).where(F.col("n") >= max(needs.min_docs, 2)).select("run", "keeper"), "shared", base)
    cuts = runs.join(shared, "run").where(~F.col("id").eqNullSafe(F.col("keeper"))).groupBy("id", "content").agg(F.collect_set("at").alias("_cut"))
    cuts = materialise(cuts, "cuts", base)
    lost = drops.select("_id", "_content", "_drop").join(cuts, mine(cuts["id"], cuts["content"]), "left").select("_id", "_content", "_drop", "_cut")
    lost = materialise(lost.where((F.size("_drop") > 0) | F.col("_cut").isNotNull()), "lost", base)
    names = docs.columns
    plain = bounded(docs).toDF(*[f"c{i}" for i in range(len(names))])
    at, at_id = names.index(text_col), names.index(id_col)
    both = plain.join(lost, mine(plain[f"c{at_id}"].cast("bigint"), F.xxhash64(plain[f"c{at}"])), "left").select(*plain.columns, "_drop", "_cut")
    schema = T.StructType([T.StructField(f"c{i}", f.dataType) for i, f in enumerate(docs.schema.fields)] + [T.StructField(f"c{len(names)}", T.IntegerType()), T.StructField(f"c{len(names) + 1}", T.IntegerType())])
    out = both.mapInArrow(_rebuild(at, len(names), needs.run_tokens), schema)
    if drop_emptied:
        out = out.where((F.col(f"c{len(names)}") == 0) | (F.col(f"c{len(names) + 1}") < F.col(f"c{len(names)}")))
    if counts:
        return out.toDF(*names, "n_records", "n_dropped")
    return out.select(*[F.col(f"c{i}") for i in range(len(names))]).toDF(*names)
