"""Packing of tokenised documents into fixed windows, best fit decreasing.

Every document is tokenised and closed with one end id.  What fills whole
windows is cut off first, each window a sequence of its own; the tails go, by
falling length, each into the open sequence with the least sufficient room,
found in a segment tree over remaining capacities.  A sequence that is still
left with much room is cut at powers of two, which need no padding.

Tasks pack on their own, in blocks of about ``block_tokens`` tail tokens, so
memory is bounded and no row is shuffled; a task's sequence ids carry its
partition number.  Re-running a lost task gives the same sequences.

Defined cases: null text is empty (its end id alone); repeated rows, equal ids
and null ids are packed each; a text of any length is cut into full windows;
extra columns are ignored; an empty table packs nothing.
"""

from __future__ import annotations

import json
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import bounded

#: the pre-tokeniser of byte-level vocabularies (a fixed value of the format)
_SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


@lru_cache(maxsize=4)
def encoder(path: str):
    """text -> ids, as ``tokenizers`` gives them for the JSON file at ``path``.

    A byte-level vocabulary whose ids follow its merge order is run by
    ``tiktoken``, which is several times faster and gives the same ids; any
    other file is run by ``tokenizers`` itself, and so is a text on which the
    faster one gives up (its pattern fails on about a million blanks in a row).
    """
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(path)
    plainly = lambda text: np.array(slow.encode(text, add_special_tokens=False).ids, "<u4")
    model, pre = spec["model"], spec.get("pre_tokenizer") or {}
    plain = model.get("type") == "BPE" and spec.get("normalizer") is None and pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True) and not model.get("ignore_merges") and model.get("dropout") is None and not model.get("continuing_subword_prefix") and not model.get("end_of_word_suffix")
    if plain:
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        table = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in shown)}
        special = {t["content"]: t["id"] for t in spec.get("added_tokens", []) if not (t["lstrip"] or t["rstrip"] or t["single_word"] or t["normalized"])}
        vocab = {k: v for k, v in model["vocab"].items() if k not in special}
        merged = [vocab.get("".join(m if isinstance(m, list) else m.split(" "))) for m in model["merges"]]
        if len(special) == len(spec.get("added_tokens", [])) and None not in merged and merged == list(range(256, 256 + len(merged))) and len(vocab) == 256 + len(merged):
            import tiktoken

            fast = tiktoken.Encoding("file", pat_str=_SPLIT, mergeable_ranks={bytes(table[c] for c in k): v for k, v in vocab.items()}, special_tokens=special)

            def encode(text: str) -> np.ndarray:
                try:
                    return np.asarray(fast.encode_to_numpy(text, allowed_special="all"), "<u4")
                except ValueError:
                    return plainly(text)

            return encode
    return plainly


class Capacities:
    """Open sequences by remaining room; a segment tree of their numbers."""

    def __init__(self, window: int):
        self.leaves = 1 << window.bit_length()
        self.tree = [0] * (2 * self.leaves)
        self.held: list[list[int]] = [[] for _ in range(window + 1)]

    def _add(self, room: int, by: int) -> None:
        at = room + self.leaves
        while at:
            self.tree[at] += by
            at >>= 1

    def put(self, room: int, sequence: int) -> None:
        self.held[room].append(sequence)
        self._add(room, 1)

    def tightest(self, need: int) -> tuple[int, int] | None:
        """(room, sequence) of the least room that suffices, taken out."""
        at = need + self.leaves
        if not self.tree[at]:
            while at > 1 and (at & 1 or not self.tree[at + 1]):
                at >>= 1
            if at <= 1:
                return None
            at += 1
            while at < self.leaves:
                at = 2 * at if self.tree[2 * at] else 2 * at + 1
        room = at - self.leaves
        self._add(room, -1)
        return room, self.held[room].pop()


def best_fit(lengths: list[int], window: int) -> list[list[int]]:
    """Sequences as lists of item numbers; every length is in 1..window."""
    out: list[list[int]] = []
    open_ = Capacities(window)
    for i in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        found = open_.tightest(lengths[i])
        if found is None:
            out.append([])
            found = window, len(out) - 1
        room, s = found
        out[s].append(i)
        if room > lengths[i]:
            open_.put(room - lengths[i], s)
    return out


def _pack(path: str, window: int, end_id: int, slack: int, block_tokens: int):
    def run(batches):
        encode, part, sequences = encoder(path), TaskContext.get().partitionId(), 0
        tails: list[tuple] = []  # id, start, ids, tokens of the document
        held = 0

        def piece(doc, start, ids, total, offset):
            return doc, start, len(ids), zlib.crc32(ids.tobytes()), total, (part << 34) + sequences, offset

        def close():
            nonlocal sequences
            for members in best_fit([len(t[2]) for t in tails], window):
                used = sum(len(tails[i][2]) for i in members)
                sizes = [used]
                if window - used > slack and used & (used - 1):
                    sizes = [1 << b for b in range(used.bit_length() - 1, -1, -1) if used >> b & 1]
                room, offset = sizes.pop(0), 0
                for i in members:
                    doc, start, ids, total = tails[i]
                    while len(ids):
                        if not room:
                            sequences += 1
                            room, offset = sizes.pop(0), 0
                        yield piece(doc, start, ids[:room], total, offset)
                        n = min(room, len(ids))
                        start, ids, room, offset = start + n, ids[n:], room - n, offset + n
                sequences += 1
            tails.clear()

        def batch_of(rows):
            cols = list(zip(*rows))
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

        for batch in batches:
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                ids = np.append(encode(text.as_py() or ""), np.uint32(end_id)).astype("<u4")
                total, whole = len(ids), len(ids) // window * window
                for start in range(0, whole, window):
                    rows.append(piece(doc, start, ids[start : start + window], total, 0))
                    sequences += 1
                if total > whole:
                    tails.append((doc, whole, ids[whole:].copy(), total))
                    held += total - whole
                if held >= block_tokens:
                    rows += close()
                    held = 0
            if rows:
                yield batch_of(rows)
        if tails:
            yield batch_of(list(close()))

    return run


def pack_documents(docs: DataFrame, tokenizer: str, window: int = 2048, end_id: int = 1, slack: int | None = None, block_tokens: int = 4_000_000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a piece: doc_id, start, length, ids_crc32, doc_tokens,
    sequence_id, offset.  ``slack``: room above which a sequence is cut at
    powers of two (a sixteenth of the window unless given)."""
    src = bounded(docs).select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    return src.mapInArrow(_pack(tokenizer, window, end_id, window // 16 if slack is None else slack, block_tokens), "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint")
