"""Benchmark decontamination by spaced seeds.

A seed is a fixed mask over neighbouring words that ignores some positions, so a hit survives
substituted words. Seeds of all benchmark items are joined with those of the documents; around a
hit the item is laid on the document and accepted if a stretch of at least `least_words` words
(the whole item, if it is shorter) agrees in at least `agreement` of its positions. The masks hit
every stretch of 13 words with at most two substitutions.

The benchmark's seeds form a sorted table of checked size (`slice_words` words of different items), so the join
maps documents and shuffles none. A larger benchmark is taken in slices, one after the other, each
a job of its own over the documents that are left, so a worker holds one slice's seeds at a time.
Items of equal text are one item with several ids.
Null or empty text: no seed, not contaminated. Items without words are ignored; items shorter than
the masks match as a whole. Repeated items and rows each count; extra columns are ignored. Long
texts are searched whole. Several accepted stretches of an item in a document give several spans.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import only, tidy, written

WORD = re.compile(r"[^\W_]+")
# Spaced seeds; together they hit every 13 words with at most two substitutions.
MASKS = ("10100001111", "1101100101", "110111001", "10110100011")


class SeedIndex:
    """The seeds of some benchmark items."""

    def __init__(self, items: list[tuple[int, str]], least_words: int = 13, agreement: float = 0.8):
        self.least, self.cost = least_words, agreement / (1 - agreement)
        same: dict[tuple[str, ...], list[int]] = {}
        for k, t in items:
            ws = tuple(WORD.findall((t or "").lower()))
            if ws:
                same.setdefault(ws, []).append(k)
        self.items = [(ids, ws) for ws, ids in same.items()]
        self.words: dict[str, int] = {}
        rows = [np.array([self.words.setdefault(w, len(self.words)) for w in ws], np.int64) for _, ws in self.items]
        self.rows = rows
        rng = np.random.default_rng(7)
        self.mix = rng.integers(1, 1 << 63, max(map(len, MASKS)), dtype=np.uint64) | np.uint64(1)
        masks = [np.flatnonzero(np.frombuffer(m.encode(), np.uint8) == ord("1")) for m in MASKS]
        shortest = max(int(m[-1]) + 1 for m in masks)
        masks += [np.arange(n) for n in sorted({len(r) for r in rows if len(r) < shortest})]
        self.masks = []
        for mask in masks:
            span = int(mask[-1]) + 1
            seeds, owners, places = [], [], []
            for k, r in enumerate(rows):
                if len(r) < span or (len(mask) == span and len(r) != span):
                    continue
                seeds.append(self._seeds(r, mask))
                owners.append(np.full(len(seeds[-1]), k))
                places.append(np.arange(len(seeds[-1])))
            if seeds:
                s, o, p = map(np.concatenate, (seeds, owners, places))
                order = np.argsort(s, kind="stable")
                self.masks.append((mask, span, s[order], o[order], p[order]))

    def _seeds(self, row: np.ndarray, mask: np.ndarray) -> np.ndarray:
        n = len(row) - int(mask[-1])
        out = np.zeros(n, np.uint64)
        for k, at in enumerate(mask):
            out += (row[at : at + n].astype(np.uint64) + np.uint64(1)) * self.mix[k]
        return (out ^ (out >> np.uint64(29))) * np.uint64(0x9E3779B97F4A7C15)

    def hits(self, text: str | None, first: bool = False) -> list[tuple[int, int, int, int, int]]:
        """(item_id, first word, end word, agreeing words, words) of each accepted stretch, or of the first one found."""
        if not text or not self.items:
            return []
        low = text.lower()
        known = self.words
        row = np.fromiter((known.get(w, -1) for w in WORD.findall(low)), np.int64)
        lays = []
        for mask, span, seeds, owners, places in self.masks:
            n = len(row) - span + 1
            if n <= 0:
                continue
            ok = np.ones(n, bool)
            for at in mask:
                ok &= row[at : at + n] >= 0
            at = np.flatnonzero(ok)
            if not len(at):
                continue
            mine = self._seeds(row, mask)[at]
            low_at, high_at = np.searchsorted(seeds, mine), np.searchsorted(seeds, mine, "right")
            many = high_at - low_at
            if many.any():  # every place of the seed in the items, laid on the document
                j = np.repeat(low_at - np.append(0, np.cumsum(many)[:-1]), many) + np.arange(many.sum())
                lays.append(np.stack([owners[j], np.repeat(at, many) - places[j]], 1))
        out = []
        for k, shift in np.unique(np.concatenate(lays), axis=0).tolist() if lays else []:
            found = self._stretch(row, self.rows[k], shift)
            if found:
                out.extend((item, *found) for item in self.items[k][0])
                if first:
                    break
        return out

    def _stretch(self, row: np.ndarray, item: np.ndarray, shift: int):
        """The longest stretch of the item, laid at shift, that agrees often enough."""
        a, b = max(0, -shift), min(len(item), len(row) - shift)
        least = min(self.least, len(item))
        if b - a < least:
            return None
        same = row[a + shift : b + shift] == item[a:b]
        total = np.concatenate([[0.0], np.cumsum(np.where(same, 1.0, -self.cost))])
        # longest (i, j) with total[j] >= total[i]: i among falling minima, j among rising maxima from the right
        low, high = np.minimum.accumulate(total), np.maximum.accumulate(total[::-1])[::-1]
        i, best = 0, (0, 0)
        for j in range(len(total)):
            while i < len(total) and low[i] > high[j] + 1e-9:
                i += 1
            if i < len(total) and j - i > best[1] - best[0]:
                best = (i, j)
        i, j = best
        if j - i < least:
            return None
        while not same[i]:
            i += 1
        while not same[j - 1]:
            j -= 1
        return (a + shift + i, a + shift + j, int(same[i:j].sum()), j - i) if j - i >= min(least, 8) else None


def indexed(part: DataFrame, least_words: int, agreement: float):
    """The broadcast seed index of one slice of the benchmark, which has a bounded size."""
    items = [(x["item_id"], x["text"]) for x in part.where(F.length("text") > 0).collect()]
    return part.sparkSession.sparkContext.broadcast(SeedIndex(items, least_words, agreement))


def _without(sent):
    def run(batches):
        for batch in batches:
            yield batch.filter(pa.array([not sent.value.hits(x.as_py(), True) for x in batch.column("text")], pa.bool_()))

    return tidy(run)


def without_leaks(docs: DataFrame, benchmark: DataFrame, least_words: int = 13, agreement: float = 0.8, slice_words: int = 1_000_000) -> DataFrame:
    """The rows of docs, with all their columns, that hold no stretch of the benchmark."""
    slices = list(_sized(benchmark, slice_words))
    for k, part in enumerate(slices):
        sent = indexed(part, least_words, agreement)
        docs = docs.mapInArrow(_without(sent), docs.schema)
        if k < len(slices) - 1:
            docs = written(docs, "leaks-left")
            sent.unpersist()
    return docs


def _found(sent):
    span = pa.struct([("item_id", pa.int64()), ("start", pa.int32()), ("end", pa.int32()), ("agreeing", pa.int32()), ("words", pa.int32())])

    def run(batches):
        for batch in batches:
            rows, ids, texts, out = batch.column("row"), batch.column("doc_id"), batch.column("text"), []
            for k in range(batch.num_rows):
                text = texts[k].as_py()
                found = sent.value.hits(text)
                if found:
                    at = _places(text)
                    out.append((rows[k].as_py(), ids[k].as_py(), [{"item_id": i, "start": at[a][0], "end": at[b - 1][1], "agreeing": s, "words": n} for i, a, b, s, n in found]))
            yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in out], pa.int64()), pa.array([x[1] for x in out], pa.int64()), pa.array([x[2] for x in out], pa.list_(span))], ["row", "doc_id", "spans"])

    return tidy(run)


def _sized(benchmark: DataFrame, slice_words: int):
    """The benchmark in slices of about slice_words words by the hash of the text: equal texts share a slice."""
    items = only(benchmark, item_id="bigint", text="string")
    words = items.agg(F.sum(F.length("text") - F.length(F.regexp_replace("text", r"\s", "")) + 1).alias("n")).first()["n"] or 0
    many = max(1, -(-words // slice_words))
    for k in range(many):
        yield items.where(F.pmod(F.xxhash64("text"), F.lit(many)) == k) if many > 1 else items


def find_leaks(docs: DataFrame, benchmark: DataFrame, least_words: int = 13, agreement: float = 0.8, slice_words: int = 1_000_000) -> DataFrame:
    """One row per contaminated document row: doc_id, item_ids array<bigint>, spans
    array<struct<item_id,start,end,agreeing,words>> (code points, end exclusive)."""
    shape = "row bigint, doc_id bigint, spans array<struct<item_id:bigint,start:int,end:int,agreeing:int,words:int>>"
    rows = only(docs, doc_id="bigint", text="string")
    slices = list(_sized(benchmark, slice_words))
    if len(slices) > 1:  # the rows keep their numbers through all jobs
        rows = written(rows.withColumn("row", F.monotonically_increasing_id()), "leaks-rows")
    else:
        rows = rows.withColumn("row", F.lit(0).cast("bigint"))
    found = None
    for part in slices:
        sent = indexed(part, least_words, agreement)
        mine = rows.select("row", "doc_id", "text").mapInArrow(_found(sent), shape)
        if len(slices) > 1:
            mine = written(mine, "leaks-found")
            sent.unpersist()
        found = mine if found is None else found.unionAll(mine)
    if len(slices) > 1:
        found = found.groupBy("row").agg(F.first("doc_id").alias("doc_id"), F.flatten(F.collect_list("spans")).alias("spans"))
    ids = F.array_sort(F.array_distinct(F.filter(F.transform("spans", lambda x: x["item_id"]), lambda x: x.isNotNull())))
    return found.select("doc_id", ids.alias("item_ids"), F.array_sort("spans").alias("spans"))


def _places(text: str) -> list[tuple[int, int]]:
    """(start, end) of each word in the text itself; lower-casing may change lengths, so words are found by character."""
    low = text.lower()
    if len(low) == len(text):
        return [m.span() for m in WORD.finditer(low)]
    origin = [k for k, c in enumerate(text) for _ in c.lower()]
    while len(origin) < len(low):
        origin.append(len(text) - 1)
    return [(origin[m.start()], origin[m.end() - 1] + 1) for m in WORD.finditer(low)]
