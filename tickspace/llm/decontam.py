"""Benchmark passages in documents, found by winnowed fingerprints.

Fingerprints are k-gram hashes of words; of each window of ``w`` consecutive
k-grams the smallest hash is kept, which depends on those words only.  With
k + w - 1 = ``window`` words, every span of ``window`` shared words has a
shared fingerprint on both sides.  A hit is then extended to the left and the
right while the words agree, up to ``window`` words each way, and counts where
the span reaches ``window`` words; longer shared spans are the union of these.
Items of fewer words are looked up whole.

The benchmark side is broadcast in blocks of at most ``block_words`` words: items
are cut, where they are tokenised, into pieces of no more (a piece repeats the
last words of the one before, so no window is lost), and pieces are put together
up to that number as they arrive.  A benchmark within one block, the usual case,
needs a single scan of the documents and no shuffle; a larger one takes a scan a
block, over rows numbered and written once, whose hits are united per row.

Of places of one item that agree in all words which an extension may look at one
is indexed, and matches are extended ``PAIRS`` at a time, overlapping spans being
united: texts and items that repeat one word cost no more memory than others.

Defined cases: null, empty or wordless texts have no words and are clean;
wordless items never occur; repeated item ids count once; repeated rows are
judged each; extra columns are ignored; empty tables give empty results.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import bounded, materialise
from .textkernel import NON_ALNUM, U, buffers, chunks, grams, mix, span, sums, words

PAIRS = 1 << 20  #: matches that are extended at once


def winnow(h: np.ndarray, text: np.ndarray, k: int, w: int) -> tuple[np.ndarray, np.ndarray]:
    """(positions, hashes) of the fingerprints: the minimum of each run of w
    k-grams that lie in one text; of equal ones the rightmost."""
    g = grams(h, k)
    n = len(g) - w + 1
    if n <= 0:
        return np.zeros(0, np.int64), g[:0]
    low, arg = g[:n].copy(), np.zeros(n, np.int8)
    for i in range(1, w):
        less = g[i : i + n] <= low
        low[less] = g[i : i + n][less]
        arg[less] = i
    inside = text[:n] == text[w + k - 2 : w + k - 2 + n]
    at = np.unique(np.flatnonzero(inside) + arg[inside])
    return at, g[at]


class Index:
    """Word hashes, fingerprints and short items of one benchmark block."""

    def __init__(self, ids: list, texts: list, window: int, k: int):
        self.ids, self.window, self.k, self.w = ids, window, k, window - k + 1
        data, off = buffers(pa.array(texts, pa.string()))
        found = words(data, off, NON_ALNUM)
        self.hash, self.item = found.hash, found.text
        self.first = found.first(len(ids))
        at, g = winnow(self.hash, self.item, k, self.w)
        if len(at):
            left = np.maximum(self.first[self.item[at]], at - window)
            right = np.minimum(self.first[self.item[at] + 1], at + window)
            with np.errstate(over="ignore"):
                place = mix(span(sums(self.hash), left, right, 41) ^ mix((at - left).astype(U) * U(1 << 20) + (right - at).astype(U), 42), 43) ^ mix(self.item[at].astype(U), 44)
            one = np.sort(np.unique(place, return_index=True)[1])
            at, g = at[one], g[one]
        order = np.argsort(g, kind="stable")
        self.at, self.print = at[order], g[order]
        size = np.diff(self.first)
        self.short = {}
        for m in range(1, window):
            rows = np.flatnonzero(size == m)
            if len(rows):
                key = np.array([grams(self.hash[self.first[i] : self.first[i + 1]], m)[0] for i in rows], U)
                order = np.argsort(key, kind="stable")
                self.short[m] = (key[order], rows[order])

    def _matches(self, keys: np.ndarray, table: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """All (i, j) with keys[i] == table[j], table being sorted; runs of
        about ``PAIRS`` of them."""
        if not len(table):
            return
        lo = np.searchsorted(table, keys, "left")
        some = np.flatnonzero((lo < len(table)) & (table[np.minimum(lo, len(table) - 1)] == keys))
        lo = lo[some]
        n = np.searchsorted(table, keys[some], "right") - lo
        total = np.append(0, np.cumsum(n))
        row = 0
        while row < len(some):
            end = max(row + 1, int(np.searchsorted(total, total[row] + PAIRS, "right")) - 1)
            m, part = n[row:end], slice(row, end)
            i = np.repeat(some[part], m)
            yield i, np.repeat(lo[part], m) + np.arange(len(i)) - np.repeat(total[row:end] - total[row], m)
            row = end

    def _extended(self, h: np.ndarray, text: np.ndarray, p: np.ndarray, q: np.ndarray) -> np.ndarray:
        """(first word, end word, item) of the k-gram matches (p, q) that reach
        ``window`` words.  A window further each way reaches every window that
        holds the match."""
        left, right = np.zeros(len(p), np.int64), np.full(len(p), self.k, np.int64)
        for step, edge in ((left, 0), (right, 1)):
            live = np.arange(len(p))
            while len(live):
                a = p[live] + (step[live] if edge else -step[live] - 1)
                b = q[live] + (step[live] if edge else -step[live] - 1)
                ok = (a >= 0) & (a < len(h)) & (b >= 0) & (b < len(self.hash))
                a, b, live = a[ok], b[ok], live[ok]
                ok = (h[a] == self.hash[b]) & (text[a] == text[p[live]]) & (self.item[b] == self.item[q[live]])
                live = live[ok]
                step[live] += 1
                live = live[step[live] < self.window]
        long = (h[p] == self.hash[q]) & (left + right >= self.window)
        return np.stack([p[long] - left[long], p[long] + right[long], self.item[q[long]]])

    def spans(self, h: np.ndarray, text: np.ndarray) -> np.ndarray:
        """(first word, end word, item) of the shared spans in h, spans of one
        text and item that overlap or touch being one."""
        out = [np.zeros((3, 0), np.int64)]
        at, g = winnow(h, text, self.k, self.w)
        for i, j in self._matches(g, self.print):
            out.append(_united(self._extended(h, text, at[i], self.at[j]), text))
        for m, (keys, rows) in self.short.items():
            g = grams(h, m)
            inside = np.flatnonzero(text[: len(g)] == text[m - 1 :] if len(g) else np.zeros(0, bool))
            for i, j in self._matches(g[inside], keys):
                out.append(_united(np.stack([inside[i], inside[i] + m, rows[j]]), text))
        return _united(np.concatenate(out, 1), text)


def _united(spans: np.ndarray, text: np.ndarray) -> np.ndarray:
    if not spans.shape[1]:
        return spans
    a, b, item = spans[:, np.lexsort((spans[0], spans[2], text[spans[0]]))]
    of = text[a]
    group = np.cumsum(np.append(True, (item[1:] != item[:-1]) | (of[1:] != of[:-1]))) - 1
    reach = np.maximum.accumulate(b + group * (len(text) + 1)) - group * (len(text) + 1)  # a group's ends only
    new = np.append(True, (group[1:] != group[:-1]) | (a[1:] > reach[:-1]))
    last = np.append(np.flatnonzero(new)[1:], len(a)) - 1
    return np.stack([a[new], reach[last], item[new]])


def _pieces(window: int, block_words: int):
    def run(batches):
        for batch in batches:
            ids, texts, sizes = [], [], []
            for row, end, data, off in chunks(batch.column(1)):
                w = words(data, off, NON_ALNUM)
                first = w.first(end - row)
                for t in range(end - row):
                    lo, n = int(first[t]), int(first[t + 1] - first[t])
                    for at in range(0, max(n - window + 1, 1) if n else 0, block_words):
                        last = min(at + block_words + window - 1, n)
                        ids.append(row + t)
                        texts.append(data[w.start[lo + at] : w.end[lo + last - 1]].tobytes().decode())
                        sizes.append(last - at)
            if ids:
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(ids)), pa.array(texts, pa.string()), pa.array(sizes, pa.int64())], ["i", "t", "n"])

    return run


def _blocks(benchmark: DataFrame, item_col: str, text_col: str, window: int, k: int, block_words: int) -> Iterator[Index]:
    """Indexes of at most ``block_words`` words (and a window), one at a time:
    the benchmark passes through the driver and is never there as a whole."""
    items = benchmark.select(F.col(item_col).alias("i"), F.col(text_col).alias("t")).where("i is not null")
    pieces = bounded(items).mapInArrow(_pieces(window, block_words), f"i {items.schema['i'].dataType.simpleString()}, t string, n bigint")
    ids, texts, held = [], [], 0
    for r in pieces.toLocalIterator():
        if held and held + r["n"] > block_words:
            yield Index(ids, texts, window, k)
            ids, texts, held = [], [], 0
        ids.append(r["i"])
        texts.append(r["t"])
        held += r["n"]
    if ids:
        yield Index(ids, texts, window, k)


def _kernel(index_b):
    def run(batches):
        index = index_b.value
        for batch in batches:
            n_words, spans = np.zeros(batch.num_rows, np.int64), [None] * batch.num_rows
            for row, end, data, off in chunks(batch.column(1)):
                w = words(data, off, NON_ALNUM)
                first = w.first(end - row)
                n_words[row:end] = np.diff(first)
                if index is None:
                    continue
                a, b, item = index.spans(w.hash, w.text)
                of = w.text[a]
                for t in np.unique(of):
                    mine = of == t
                    spans[row + t] = np.stack([a[mine] - first[t], b[mine] - first[t], item[mine]], 1).tolist()
            rows = [None if s is None else [{"a": a, "b": b, "item": str(index.ids[i])} for a, b, i in s] for s in spans]
            kind = pa.list_(pa.struct([("a", pa.int32()), ("b", pa.int32()), ("item", pa.string())]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n_words), pa.array(rows, kind)], ["doc_id", "n_words", "spans"])

    return run


def contaminated_spans(docs: DataFrame, benchmark: DataFrame, window: int = 10, k: int = 5, block_words: int = 4_000_000, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """(doc_id, n_words, spans) of every document; spans: word positions
    [a, b) that ``item`` shares, null where there are none."""
    src = bounded(docs).select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    kind = f"doc_id {src.schema['doc_id'].dataType.simpleString()}, n_words bigint, spans array<struct<a:int,b:int,item:string>>"
    blocks = _broadcast(docs, benchmark, item_col, item_text_col, window, k, block_words)
    if len(blocks) == 1:
        return src.mapInArrow(_kernel(blocks[0]), kind)
    src = bounded(materialise(src.select(F.struct("doc_id", F.monotonically_increasing_id().alias("row")).alias("doc_id"), "text"), "rows"))
    part = f"doc_id {src.schema['doc_id'].dataType.simpleString()}, n_words bigint, spans array<struct<a:int,b:int,item:string>>"
    every = None
    for block in blocks:
        one = src.mapInArrow(_kernel(block), part)
        if every is not None:
            one = one.where("spans is not null")
        every = one if every is None else every.unionByName(one)
    return every.groupBy("doc_id").agg(F.max("n_words").alias("n_words"), F.flatten(F.collect_list("spans")).alias("spans")).select("doc_id.doc_id", "n_words", F.when(F.size("spans") > 0, F.col("spans")).alias("spans"))


def _broadcast(docs: DataFrame, benchmark: DataFrame, item_col: str, text_col: str, window: int, k: int, block_words: int) -> list:
    if not 1 <= k <= window:
        raise ValueError("k must lie between 1 and window")
    sc = docs.sparkSession.sparkContext
    return [sc.broadcast(b) for b in _blocks(benchmark, item_col, text_col, window, k, block_words)] or [sc.broadcast(None)]


def _hits(spans: list[dict] | None) -> int:
    """Words that the spans cover."""
    covered, last = 0, 0
    for a, b in sorted((s["a"], s["b"]) for s in spans or ()):
        covered += max(0, b - max(a, last))
        last = max(last, b)
    return covered


def _digest(batches):
    for batch in batches:
        hit, count, sha = [], [], []
        for spans in batch.column(2).to_pylist():
            items = sorted({s["item"] for s in spans or ()})
            hit.append(_hits(spans))
            count.append(len(items))
            sha.append(hashlib.sha256(",".join(items).encode()).hexdigest())
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(hit, pa.int64()), pa.array(count, pa.int64()), pa.array(sha), pa.array([h > 0 for h in hit], pa.bool_())], ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"])


def decontamination_report(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    spans = contaminated_spans(docs, benchmark, **options)
    kind = spans.schema["doc_id"].dataType.simpleString()
    return spans.mapInArrow(_digest, f"doc_id {kind}, n_words bigint, n_hit bigint, n_items bigint, items_sha256 string, contaminated boolean")


def _clean(block, at: int, max_share: float):
    scan = _kernel(block)

    def run(batches):
        for batch in batches:
            for judged in scan([pa.RecordBatch.from_arrays([pa.nulls(batch.num_rows), batch.column(at)], ["doc_id", "text"])]):
                hit = [_hits(s) for s in judged.column(2).to_pylist()]
                yield batch.filter(pa.array([not h or h <= n * max_share for h, n in zip(hit, judged.column(1).to_pylist())], pa.bool_()))

    return run


def remove_contaminated(docs: DataFrame, benchmark: DataFrame, max_share: float = 0.0, window: int = 10, k: int = 5, block_words: int = 4_000_000, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """``docs`` without the rows of whose words more than ``max_share`` are hit;
    each row is judged by its own text.  One scan where the benchmark is one
    block; else the rows are numbered, written, and the hit ones taken out."""
    names = docs.columns
    plain = bounded(docs).toDF(*[f"c{i}" for i in range(len(names))])
    blocks = _broadcast(docs, benchmark, item_col, item_text_col, window, k, block_words)
    at = names.index(text_col)
    if len(blocks) == 1:
        return plain.mapInArrow(_clean(blocks[0], at, max_share), plain.schema).toDF(*names)
    rows = materialise(plain.withColumn("row", F.monotonically_increasing_id()), "rows")
    report = decontamination_report(rows, benchmark, window=window, k=k, block_words=block_words, id_col="row", text_col=f"c{at}", item_col=item_col, item_text_col=item_text_col)
    bad = materialise(report.where((F.col("n_hit") > F.col("n_words") * max_share) & (F.col("n_hit") > 0)).select(F.col("doc_id").alias("row")), "hit")
    return rows.join(bad, "row", "left_anti").select(*plain.columns).toDF(*names)
