"""Exact Jaccard self-join of documents on word n-grams, as components, by token groups.

1. One scan makes each document's set of n-gram hashes and its fingerprint. All tokens are put in
   one order, rare ones first; two linked sets must share a token among the first
   n - ceil(t * n) + 1 of theirs. Most documents have that many tokens that no other document
   holds and have no candidate at all; passages and lines that many unlike documents share come
   late in the order and bring nobody together. How rare tokens are is counted over all documents,
   on a fixed share of the hash space for long documents (the other tokens come after the counted
   ones, in hash order), and tokens found very common in a bounded sample come last: the order only
   has to be the same for all, so no choice here can lose a link. Documents whose early tokens are
   known without counts are counted too: a token is one document's own only if no other holds it.
2. Documents of equal sets are one class. Classes that share an early token are candidates;
   candidates form clusters (distributed components).
3. In a cluster the token-group matrix decides: similar sets are grouped, each group keeps the union
   of its tokens, the overlap of a query with a group's union bounds that with its members, and
   only groups that can hold a link are opened, without pairs that are known to be connected.
   A cluster beyond a task's bound is cut into cells by the sizes of its sets: linked sets differ in size by no more than
   the threshold allows, so each set goes to its own band of sizes and the one below, and no link is cut. A cell
   beyond the bound (sets of like size) is dealt into random units; then a few documents of each
   component so far stand for it and meet in units again, until that joins no more. Documents outside the cluster's
   main component (here: of a cell) then ask the groups (parts of components) that share an early token with their own,
   and no others, without documents that share too few tokens with other components to be linked to any: no task holds an unbounded cluster, and its sets travel to where a link can be.

Equal sets and very common early tokens are collapsed within a task before the shuffle, so what is
held by a third of all rows adds an entry a task. Null or empty text and texts without words: the
empty set, linked with nothing. Repeated rows and rows that share a doc_id are each judged by their
own text; null doc_id: its set is counted, component null. Ties: the least doc_id. Extra columns
are ignored. Long texts are taken whole.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import only, tidy, written
from .graph import components

U = np.uint64
MIX = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3, 0x589965CC75374CC3], U)
#: Shingles and documents that one verifying task holds at most.
UNIT_SHINGLES, UNIT_DOCS = 1_000_000, 200
#: Documents that stand for a component when units are joined.
HEADS = 4
#: Entries gathered by a scanning task before they are sent on.
FLUSH = 500_000


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U(31))) * MIX[3]
    x = (x ^ (x >> U(27))) * MIX[4]
    return x ^ (x >> U(33))


class Shingler:
    """The sets of hashed word n-grams of texts; words are parted by ASCII white space, A-Z lower-cased."""

    def __init__(self, words: int):
        self.words = words

        class Known(dict):
            def __missing__(self, word):
                if len(self) > 150_000:
                    self.clear()
                self[word] = value = xxhash.xxh64_intdigest(word)
                return value

        self.hash = Known().__getitem__

    def set_of(self, text: bytes) -> np.ndarray:
        words = text.lower().split()
        if not words:
            return np.empty(0, U)
        row = np.fromiter(map(self.hash, words), U, len(words))
        k, n = self.words, len(row) - self.words + 1
        if n < 1:
            return _mixed((row * MIX[np.arange(len(row)) % 8]).sum(keepdims=True) + np.array([len(row)], U) * MIX[7])
        out = np.zeros(n, U)
        for at in range(k):
            out += row[at : at + n] * MIX[at % 8] + U(at)
        return np.unique(_mixed(out))


class Order:
    """Which tokens of a set are counted, and which come early without being counted.

    Sets of up to `short` tokens are compared on all tokens (space 0), sets of more than
    short * num / den on the counted share of the hash space (space 1); those between, in both.
    """

    def __init__(self, num: int, den: int, common: np.ndarray, short: int = 200):
        self.num, self.den, self.common, self.short = num, den, common, short
        self.share = max(1, 6 * den // (10 * (den - num)))

    def early(self, n: int) -> int:
        return n - -(-self.num * n // self.den) + 1

    def entries(self, tokens: np.ndarray):
        """For each space: (space, p, counted tokens, direct): direct tokens are early whatever the counts
        say; with fewer counted tokens than p, the counted ones are among them."""
        n = len(tokens)
        p = self.early(n)
        at = np.minimum(np.searchsorted(self.common, tokens), len(self.common) - 1) if len(self.common) else None
        rare = np.ones(n, bool) if at is None else self.common[at] != tokens
        for space in (0, 1):
            if (n > self.short) if space == 0 else (n * self.den <= self.short * self.num):
                continue
            inside = np.ones(n, bool) if space == 0 else tokens % U(self.share) == 0
            first = inside & rare
            counted = tokens[first]
            if len(counted) >= p:
                yield space, p, counted, None
            else:  # then the common ones inside, then those outside, each by hash (tokens are sorted)
                rest = np.concatenate([tokens[inside & ~rare], tokens[~inside]])[: p - len(counted)]
                yield space, p, counted, np.concatenate([counted, rest]) ^ MIX[space]


SCAN = "kind int, doc_id bigint, mark bigint, n bigint, fp1 bigint, fp2 bigint, bucket bigint, tokens binary, docs binary"


def _rows(**columns):
    names = [x.split()[0] for x in SCAN.split(", ")]
    types = [pa.int32(), *[pa.int64()] * 6, pa.binary(), pa.binary()]
    n = len(next(iter(columns.values())))
    return pa.RecordBatch.from_arrays([(columns[c] if isinstance(columns[c], pa.Array) else pa.array(columns[c], t)) if c in columns else pa.nulls(n, t) for c, t in zip(names, types)], names)


def _packed(kind: int, tokens: np.ndarray, docs: np.ndarray, by: np.ndarray, buckets: int, extra: np.ndarray | None = None):
    """Rows of packed (token, document) entries, one for each bucket."""
    bucket = np.mod(by, np.array(buckets, by.dtype)).astype(np.int64)
    order = np.argsort(bucket, kind="stable")
    bucket, tokens, docs = bucket[order], tokens[order], docs[order]
    extra = extra[order] if extra is not None else None
    starts = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1])) if len(bucket) else np.empty(0, np.int64)
    out = {"kind": [], "bucket": [], "n": [], "tokens": [], "docs": [], "fp1": []}
    for a, b in zip(starts.tolist(), [*starts[1:].tolist(), len(bucket)]):
        low = int(docs[a:b].min())
        narrow = int(docs[a:b].max()) - low < 1 << 32
        out["kind"].append(kind)
        out["bucket"].append(int(bucket[a]))
        out["n"].append(b - a)
        out["fp1"].append(low)
        out["tokens"].append(tokens[a:b].tobytes() + (extra[a:b].astype(np.uint32).tobytes() if extra is not None else b""))
        out["docs"].append((docs[a:b] - low).astype(np.uint32 if narrow else np.int64).tobytes())
    return _rows(**out)


def _unpacked(table: pa.Table, with_extra: bool = False):
    tokens, docs, extra = [np.empty(0, U)], [np.empty(0, np.int64)], [np.empty(0, np.uint32)]
    for low, n, t, d in zip(*(table[c].to_pylist() for c in ("fp1", "n", "tokens", "docs"))):
        tokens.append(np.frombuffer(t, U, n))
        docs.append(np.frombuffer(d, np.uint32 if len(d) == 4 * n else np.int64).astype(np.int64) + low)
        if with_extra:
            extra.append(np.frombuffer(t, np.uint32, n, 8 * n))
    return np.concatenate(tokens), np.concatenate(docs), np.concatenate(extra)


EARLY, SETS, LOCAL, DIRECT, COUNTED, WANTS, HELD = -4, -1, -2, -3, 0, 2, 4  # COUNTED, WANTS and HELD + space
PACKED = (COUNTED, COUNTED + 1, HELD, HELD + 1)


def _scan(words: int, num: int, den: int, buckets: int, sent):
    def run(batches):
        order, shingler, seen = Order(num, den, sent.value), Shingler(words), set()
        parts, size = {k: [] for k in (*PACKED, DIRECT)}, 0

        def flushed():
            for kind in PACKED:
                if parts[kind]:
                    tokens, docs = (np.concatenate(x) for x in zip(*parts[kind]))
                    yield _packed(kind, tokens, docs, _mixed(tokens), buckets)
            if parts[DIRECT]:
                tokens, docs = (np.concatenate(x) for x in zip(*parts[DIRECT]))
                at = np.lexsort((docs, tokens))
                tokens, docs = tokens[at], docs[at]
                first = np.append(True, tokens[1:] != tokens[:-1])
                lead = docs[np.maximum.accumulate(np.where(first, np.arange(len(docs)), 0))]
                pairs = np.unique(np.stack([docs[~first], lead[~first]], 1), axis=0)
                pairs = pairs[pairs[:, 0] != pairs[:, 1]]
                if len(pairs):  # found within the task
                    yield _rows(kind=np.full(len(pairs), LOCAL, np.int32), doc_id=pairs[:, 0], bucket=pairs[:, 1])
                yield _rows(kind=np.full(int(first.sum()), DIRECT, np.int32), doc_id=docs[first], bucket=tokens[first].astype(np.int64))

        for batch in batches:
            ids, texts = batch.column("doc_id"), batch.column("text")
            done = {"kind": [], "doc_id": [], "mark": batch.column("mark"), "n": [], "fp1": [], "fp2": []}
            wants = {"kind": [], "doc_id": [], "n": [], "fp1": []}
            early = {"kind": [], "doc_id": [], "tokens": []}  # DIRECT tokens are collapsed within the task; these are not
            for k in range(batch.num_rows):
                tokens = shingler.set_of(texts[k].as_buffer().to_pybytes()) if texts[k].is_valid else np.empty(0, U)
                fp = xxhash.xxh3_128_digest(tokens.tobytes())
                doc = ids[k].as_py()
                done["kind"].append(SETS)
                done["doc_id"].append(doc)
                done["n"].append(len(tokens))
                done["fp1"].append(int.from_bytes(fp[:8], "little", signed=True))
                done["fp2"].append(int.from_bytes(fp[8:], "little", signed=True))
                if not len(tokens) or doc is None or fp in seen:
                    continue
                if len(seen) > 200_000:
                    seen.clear()
                seen.add(fp)
                for space, p, counted, direct in order.entries(tokens):
                    if direct is None:
                        parts[COUNTED + space].append((counted, np.full(len(counted), doc, np.int64)))
                        wants["kind"].append(WANTS + space)
                        wants["doc_id"].append(doc)
                        wants["n"].append(p)
                        wants["fp1"].append(len(counted))
                        size += len(counted)
                    else:
                        parts[DIRECT].append((direct, np.full(len(direct), doc, np.int64)))
                        early["kind"].append(EARLY)
                        early["doc_id"].append(doc)
                        early["tokens"].append(direct.tobytes())
                        # counted as well, though nothing is asked for them: else a token shared with this document alone would seem to be the other's own
                        parts[HELD + space].append((counted, np.zeros(len(counted), np.int64)))
                        size += len(direct) + len(counted)
                if size > FLUSH:
                    yield from flushed()
                    parts, size = {k: [] for k in (*PACKED, DIRECT)}, 0
            yield _rows(**done)
            if wants["kind"]:
                yield _rows(**wants)
            if early["kind"]:
                yield _rows(**early)
        yield from flushed()

    return run


def _counts(buckets: int):
    def run(unit: pa.Table) -> pa.Table:
        """The tokens of one bucket that more than one document holds, with their counts, packed by document. Entries of kind HELD are counted only."""
        kinds = unit["kind"].to_numpy()
        tokens, docs, _ = _unpacked(unit.filter(pa.array(kinds < HELD)))
        held, none, _ = _unpacked(unit.filter(pa.array(kinds >= HELD)))
        asks = np.repeat([True, False], [len(tokens), len(held)])
        tokens, docs = np.concatenate([tokens, held]), np.concatenate([docs, none])
        at = np.argsort(tokens, kind="stable")
        tokens, docs, asks = tokens[at], docs[at], asks[at]
        starts = np.flatnonzero(np.append(True, tokens[1:] != tokens[:-1]))
        held = np.diff(np.append(starts, len(tokens)))
        count = np.repeat(held, held)
        shared = (count > 1) & asks
        out = _packed(COUNTED + int(kinds[0]) % 2, tokens[shared], docs[shared], docs[shared], buckets, np.minimum(count[shared], (1 << 32) - 1))
        return pa.Table.from_batches([out])

    return run


def _early(unit: pa.Table) -> pa.Table:
    """From the shared tokens of some documents (kinds 0, 1) and what these documents want (2, 3): their early tokens that others hold, packed, a row a document."""
    kinds = unit["kind"].to_numpy()
    space = int(kinds[0]) % 2
    tokens, docs, counts = _unpacked(unit.filter(pa.array(kinds < WANTS)), True)
    wants = unit.filter(pa.array(kinds >= WANTS))
    out_docs, out_tokens = [], []
    if len(tokens) and wants.num_rows:
        at = np.lexsort((tokens, counts, docs))
        tokens, docs = tokens[at], docs[at]
        who, p, counted = (wants[c].to_numpy() for c in ("doc_id", "n", "fp1"))
        begin, end = np.searchsorted(docs, who), np.searchsorted(docs, who, "right")
        left = p - (counted - (end - begin))  # early places that tokens of this document alone do not fill
        for d, b, n in zip(who.tolist(), begin.tolist(), np.minimum(left, end - begin).tolist()):
            if n > 0:
                out_docs.append(d)
                out_tokens.append((tokens[b : b + n] ^ MIX[space]).astype(np.int64))
    return pa.table({"doc_id": pa.array(out_docs, pa.int64()), "tokens": pa.array(out_tokens, pa.list_(pa.int64()))})


def common_tokens(rows: DataFrame, total: int, words: int, sample: int = 8_000, share: int = 1_000) -> np.ndarray:
    """Sorted hashes of the tokens that at least one in `share` sampled documents holds: at most
    `share` times a document's mean number of tokens, whatever the size of the corpus. It orders
    tokens only; no result depends on it."""
    part = rows.where(F.pmod(F.xxhash64("doc_id", F.lit(97)), F.lit(max(1, -(-total // sample)))) == 0)

    def run(batches):
        shingler, seen, held = Shingler(words), set(), []
        for batch in batches:
            for x in batch.column("text"):
                tokens = shingler.set_of(x.as_buffer().to_pybytes()) if x.is_valid else np.empty(0, U)
                fp = xxhash.xxh3_64_intdigest(tokens.tobytes())
                if fp not in seen:
                    seen.add(fp)
                    held.append(tokens)
        if held:
            token, count = np.unique(np.concatenate(held), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(token.astype(np.int64)), pa.array(count)], ["token", "n"])

    counts = part.mapInArrow(tidy(run), "token bigint, n bigint").groupBy("token").agg(F.sum("n").alias("n"))
    found = counts.where(F.col("n") >= max(3, min(total, sample) // share)).select("token").toPandas()
    return np.sort(found["token"].to_numpy().astype(U))


def token_group_links(ids: np.ndarray, sets: list[np.ndarray], num: int, den: int, known: np.ndarray | None = None, asking: np.ndarray | None = None, group: int = 16) -> list[tuple[int, int]]:
    """Links among the sets that connect what is not yet connected (a spanning forest of the link
    graph, with what `known` component labels connect already). With `asking` only these ask."""
    n = len(ids)
    sizes = np.array([len(x) for x in sets], np.int64)
    root = np.arange(n)
    if known is not None:
        _, first, back = np.unique(known, return_index=True, return_inverse=True)
        root = first[back]
    # similar sets next to one another: by their least tokens (a min-hash order), then cut into groups
    order = np.lexsort((sizes, [int(x[1]) if len(x) > 1 else 0 for x in sets], [int(x[0]) for x in sets]))
    group_of = np.empty(n, np.int64)
    group_of[order] = np.arange(n) // group
    groups = -(-n // group)
    flat, owner = np.concatenate(sets), np.repeat(np.arange(n), sizes)
    token = np.unique(flat, return_inverse=True)[1]
    # the matrix, sparse: the groups of each token, once each; and the postings of each token
    cells = np.unique(token * groups + group_of[owner])
    cell_group, cell_start = cells % groups, np.searchsorted(cells // groups, np.arange(token.max() + 2))
    by = np.argsort(token, kind="stable")
    posting, post_start = owner[by], np.searchsorted(token[by], np.arange(token.max() + 2))
    starts = np.append(0, np.cumsum(sizes))
    links = []

    def gathered(lists: np.ndarray, begin: np.ndarray, tokens: np.ndarray) -> np.ndarray:
        a, length = begin[tokens], begin[tokens + 1] - begin[tokens]
        return lists[np.repeat(a - np.append(0, np.cumsum(length)[:-1]), length) + np.arange(length.sum())]

    def top(k: int) -> int:
        while root[k] != k:
            root[k] = root[root[k]]
            k = root[k]
        return int(k)

    tops = np.array([top(k) for k in range(n)])
    for q in range(n) if asking is None else np.flatnonzero(asking):
        others = tops != tops[q]  # tops is kept flat
        if not others.any():
            continue
        mine = token[starts[q] : starts[q + 1]]
        bound = np.bincount(gathered(cell_group, cell_start, mine), minlength=groups)
        open_ = bound * den >= num * sizes[q]  # overlap of a link: at least num/den of the query's size
        ask = np.flatnonzero(others & open_[group_of])
        ask = ask[(sizes[ask] * den >= num * sizes[q]) & (sizes[ask] * num <= den * sizes[q])]
        if not len(ask):
            continue
        if len(ask) > 40:
            both = np.bincount(gathered(posting, post_start, mine), minlength=n)[ask]
        else:
            both = np.array([np.isin(mine, token[starts[k] : starts[k + 1]], assume_unique=True).sum() for k in ask])
        for k in ask[both * den >= num * (sizes[q] + sizes[ask] - both)]:
            a, b = tops[q], tops[k]
            if a != b:
                links.append((int(ids[q]), int(ids[k])))
                tops[tops == b] = a
    return links


def _verified(num: int, den: int):
    def run(unit: pa.Table) -> pa.Table:
        ids = unit["rep"].to_numpy()
        known = unit["known"].to_numpy() if unit["known"].null_count == 0 else None
        asking = unit["asking"].to_numpy(zero_copy_only=False) if unit["asking"].null_count == 0 else None
        if asking is not None:  # a document may be of the group and ask it
            order = np.lexsort((~asking, ids))
            pick = order[np.append(True, ids[order][1:] != ids[order][:-1])]
            unit, ids, known, asking = unit.take(pa.array(pick)), ids[pick], known[pick], asking[pick]
        sets = [np.frombuffer(x, U) for x in unit["tokens"].to_pylist()]
        links = token_group_links(ids, sets, num, den, known, asking) if len(ids) > 1 else []
        cluster = pa.array([unit["cluster"][0].as_py()] * len(links), pa.int64())
        return pa.table({"cluster": cluster, "a": pa.array([x[0] for x in links], pa.int64()), "b": pa.array([x[1] for x in links], pa.int64())})

    return run


def jaccard_components(docs: DataFrame, words: int = 3, num: int = 9, den: int = 10, bucket_bytes: int = 16 << 20) -> DataFrame:
    """docs(doc_id, text) -> doc_id, mark (a hash of the text), n_shingles, component_id: links where
    den * |x & y| >= num * |x | y| on sets of distinct word n-grams."""
    rows = only(docs, doc_id="bigint", text="string").withColumn("mark", F.xxhash64("text"))
    size = rows.agg(F.sum(F.octet_length("text")).alias("bytes"), F.count("*").alias("rows")).first()
    buckets = 16 + (size["bytes"] or 0) // bucket_bytes
    sent = rows.sparkSession.sparkContext.broadcast(common_tokens(rows, size["rows"], words))
    scan = written(rows.mapInArrow(tidy(_scan(words, num, den, buckets, sent)), SCAN), "shingles")
    sets = scan.where(F.col("kind") == SETS).select("doc_id", "mark", "n", "fp1", "fp2")
    classes = sets.where("n > 0 and doc_id is not null").groupBy("fp1", "fp2").agg(F.min("doc_id").alias("rep"), F.max("n").alias("n"))
    # candidates: documents that share an early token, each with the least of its token
    packed = ["kind", "doc_id", "n", "fp1", "bucket", "tokens", "docs"]
    counted = scan.where(F.col("kind").isin(*PACKED)).select(*packed).groupBy((F.col("kind") % 2).alias("space"), "bucket").applyInArrow(_counts(buckets), SCAN)
    wants = scan.where(F.col("kind").isin(WANTS, WANTS + 1)).select(*packed).withColumn("bucket", F.pmod(F.col("doc_id"), F.lit(buckets)))
    early = written(counted.select(*packed).unionAll(wants).groupBy((F.col("kind") % 2).alias("space"), "bucket").applyInArrow(_early, "doc_id bigint, tokens array<bigint>"), "early")
    direct = scan.where(F.col("kind") == DIRECT).select(F.col("bucket").alias("token"), "doc_id")
    postings = early.select(F.explode("tokens").alias("token"), "doc_id").unionAll(direct)
    leads = postings.groupBy("token").agg(F.min("doc_id").alias("lead"), F.max("doc_id").alias("last")).where("lead < last").drop("last")
    met = postings.join(leads, "token").where("doc_id <> lead").select(F.col("doc_id").alias("a"), F.col("lead").alias("b"))
    near = scan.where(F.col("kind") == LOCAL).select(F.col("doc_id").alias("a"), F.col("bucket").alias("b"))
    found = written(met.unionAll(near).distinct(), "candidates")
    ends = found.select(F.col("a").alias("doc_id")).unionAll(found.select(F.col("b").alias("doc_id"))).distinct()
    named = written(sets.where("n > 0").join(ends, "doc_id").join(classes.drop("n"), ["fp1", "fp2"]).select("doc_id", "rep").distinct(), "named")
    edges = found.join(named.select(F.col("doc_id").alias("a"), F.col("rep").alias("ra")), "a").join(named.select(F.col("doc_id").alias("b"), F.col("rep").alias("rb")), "b")
    cluster = components(edges.select(F.col("ra").alias("a"), F.col("rb").alias("b")))
    early = early.unionAll(scan.where(F.col("kind") == EARLY).select("doc_id", "tokens").mapInArrow(_listing, "doc_id bigint, tokens array<bigint>"))
    links = _links(rows, classes, cluster, early, named, words, num, den)
    joined = components(links)
    by_set = classes.join(joined, classes["rep"] == joined["node"], "left").select("fp1", "fp2", F.coalesce("component", "rep").alias("component_id"))
    out = sets.join(by_set, ["fp1", "fp2"], "left")
    return out.select(
        "doc_id", "mark", F.col("n").alias("n_shingles"), F.when((F.col("n") > 0) & F.col("doc_id").isNotNull(), F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id")
    )


def _listing(batches):
    for batch in batches:
        tokens = pa.array([np.frombuffer(x, np.int64) for x in batch.column("tokens").to_pylist()], pa.list_(pa.int64()))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), tokens], ["doc_id", "tokens"])


def _listed(df: DataFrame, most: int) -> DataFrame:
    """A side of a join: broadcast if it has no more rows than `most`, else joined by a shuffle."""
    return F.broadcast(df) if df.count() <= most else df


def _links(rows: DataFrame, classes: DataFrame, cluster: DataFrame, early: DataFrame, named: DataFrame, words: int, num: int, den: int, listed: int = 400_000) -> DataFrame:
    """Verified links (a, b) that connect what is connected in each cluster; early(doc_id, tokens): early tokens of documents, packed; named(doc_id, rep): their classes."""
    members = written(classes.join(cluster, classes["rep"] == cluster["node"]).select("rep", "n", "fp1", "fp2", F.col("component").alias("cluster")), "members")

    def fill(batches):
        shingler = Shingler(words)
        for batch in batches:
            if not batch.num_rows:
                continue
            texts = batch.column("text")
            tokens, keep = [], []
            for k, (f1, f2) in enumerate(zip(batch.column("fp1").to_pylist(), batch.column("fp2").to_pylist())):
                mine = shingler.set_of(texts[k].as_buffer().to_pybytes()).tobytes() if texts[k].is_valid else b""
                fp = xxhash.xxh3_128_digest(mine)
                if (int.from_bytes(fp[:8], "little", signed=True), int.from_bytes(fp[8:], "little", signed=True)) == (f1, f2):
                    tokens.append(mine)
                    keep.append(k)
            part = batch.select(["rep", "n", "cluster"]).take(pa.array(keep, pa.int64()))
            yield part.append_column("tokens", pa.array(tokens, pa.binary()))

    side = _listed(members, listed)
    full = rows.join(side, rows["doc_id"] == members["rep"]).select("rep", "n", "cluster", "fp1", "fp2", "text")
    full = written(full.mapInArrow(tidy(fill), "rep bigint, n bigint, cluster bigint, tokens binary"), "cluster-sets")

    def loads(rows: DataFrame) -> DataFrame:
        return rows.groupBy("cluster").agg(F.sum("n").alias("shingles"), F.count("*").alias("docs"))

    units = F.greatest(F.ceil(F.col("shingles") / UNIT_SHINGLES), F.ceil(F.col("docs") / UNIT_DOCS)).cast("bigint").alias("units")
    wide = written(loads(members).select("cluster", units).where("units > 1").select("cluster"), "large")
    cells = members.select("cluster", "rep", "n")
    if not wide.isEmpty():  # bands of sizes: linked sets are in one band or in neighbouring ones
        side, band = _listed(wide, listed), F.floor(F.log("n") / float(np.log(den / num))) if num < den else F.col("n")
        cut = cells.join(side, "cluster").select(F.explode(F.array(band, band - 1)).alias("band"), "cluster", "rep", "n")
        cells = cells.join(side, "cluster", "left_anti").unionAll(cut.select(F.xxhash64("cluster", "band").alias("cluster"), "rep", "n"))
    cells = written(cells, "cells")
    large = written(loads(cells).select("cluster", units).where("units > 1"), "large-cells")
    plain = [F.lit(None).cast("bigint").alias("known"), F.lit(None).cast("boolean").alias("asking")]
    shape, check = "cluster bigint, a bigint, b bigint", _verified(num, den)
    beyond = _listed(large, listed)
    dealt = cells.join(beyond, "cluster", "left").select("cluster", "rep", F.pmod(F.xxhash64("rep"), F.coalesce("units", F.lit(1).cast("bigint"))).alias("unit"))
    dealt = written(dealt, "dealt")
    found = written(full.select("rep", "tokens").join(_listed(dealt, listed), "rep").select("cluster", "unit", "rep", "tokens", *plain).groupBy("cluster", "unit").applyInArrow(check, shape), "links")
    if large.isEmpty():
        return found.select("a", "b")
    # what is connected by now, in any cell
    joined = components(found.select("a", "b"))
    state = cells.join(beyond, "cluster", "left_semi")
    state = written(state.join(joined, F.col("rep") == joined["node"], "left").select("cluster", "rep", "n", F.coalesce("component", "rep").alias("known")), "known")
    before = None
    for turn in range(1, 12):  # a few documents of each component meet, until that joins no more
        heads = state.groupBy("cluster", "known", F.pmod(F.xxhash64("rep", F.lit(turn)), F.lit(HEADS))).agg(F.min(F.struct("rep", "n")).alias("h")).select("cluster", "known", "h.rep", "h.n")
        heads = written(heads, "heads")
        size = heads.groupBy("cluster").agg(F.sum("n").alias("shingles"), F.count("*").alias("docs"), F.countDistinct("known").alias("parts")).where("parts > 1")
        size = written(size.select("cluster", "parts", units), "heads-units")
        left = size.agg(F.sum("parts").alias("parts"), F.max("units").alias("units")).first()
        if not left["parts"] or before is not None and left["parts"] > 0.9 * before:
            break
        before = left["parts"]
        meet = heads.join(_listed(size, listed), "cluster").withColumn("unit", F.pmod(F.xxhash64("rep", F.lit(turn)), F.col("units"))).drop("n")
        sets = full.select("rep", "tokens").join(_listed(written(meet, "meet"), listed), "rep")
        new = written(sets.select("cluster", "unit", "rep", "tokens", "known", plain[1]).groupBy("cluster", "unit").applyInArrow(check, shape), "links")
        found = found.unionAll(new)
        label = state.select("rep", "known").distinct()
        ends = new.join(label.withColumnsRenamed({"rep": "a", "known": "ka"}), "a").join(label.withColumnsRenamed({"rep": "b", "known": "kb"}), "b")
        merged = components(ends.select(F.col("ka").alias("a"), F.col("kb").alias("b")))
        state = written(state.join(merged, state["known"] == merged["node"], "left").select("cluster", "rep", "n", F.coalesce("component", "known").alias("known")), "known")
        if left["units"] == 1:
            break
    return found.unionAll(_rest(full, _able(full, state, num, den, listed), early, named, check, shape, listed)).select("a", "b")


def _dealt(buckets: int, slice_docs: int = 500):
    def run(batches):
        """Rows of packed tokens with the documents that hold them, dealt over buckets by cell and token."""
        for whole in batches:
            for batch in (whole.slice(at, slice_docs) for at in range(0, whole.num_rows, slice_docs)):
                tokens = [np.frombuffer(x, U) for x in batch.column("tokens").to_pylist()]
                docs = np.stack([batch.column(c).to_numpy() for c in ("cluster", "rep", "known")], 1)
                at = np.repeat(np.arange(len(tokens)), [len(x) for x in tokens])
                keys = _mixed(np.concatenate(tokens) ^ docs[at, 0].astype(U))
                bucket = (keys % U(buckets)).astype(np.int64)
                order = np.argsort(bucket, kind="stable")
                bucket, keys, at = bucket[order], keys[order], at[order].astype(np.uint32)
                first = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1])).tolist()
                ends = [*first[1:], len(bucket)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(bucket[first]), pa.array([keys[a:b].tobytes() for a, b in zip(first, ends)]), pa.array([at[a:b].tobytes() for a, b in zip(first, ends)]), pa.array([docs.tobytes()] * len(first))],
                    ["bucket", "tokens", "at", "docs"],
                )

    return run


def _owned(unit: pa.Table) -> pa.Table:
    """How many tokens of each document only its own component holds in its cell."""
    keys, at, docs, base = [], [], [], 0
    for k, a, d in zip(*(unit[c].to_pylist() for c in ("tokens", "at", "docs"))):
        keys.append(np.frombuffer(k, U))
        at.append(np.frombuffer(a, np.uint32).astype(np.int64) + base)
        docs.append(np.frombuffer(d, np.int64).reshape(-1, 3))
        base += len(docs[-1])
    keys, at, docs = np.concatenate(keys), np.concatenate(at), np.concatenate(docs)
    order = np.argsort(keys, kind="stable")
    keys, at = keys[order], at[order]
    starts = np.flatnonzero(np.append(True, keys[1:] != keys[:-1]))
    known = docs[at, 2]
    alone = np.minimum.reduceat(known, starts) == np.maximum.reduceat(known, starts)
    own = np.bincount(at[np.repeat(alone, np.diff(np.append(starts, len(keys))))], minlength=base)
    some = np.flatnonzero(own)
    return pa.table({"cluster": pa.array(docs[some, 0]), "rep": pa.array(docs[some, 1]), "own": pa.array(own[some])})


def _able(full: DataFrame, state: DataFrame, num: int, den: int, listed: int, turns: int = 2) -> DataFrame:
    """The rows of state that may link with another component of their cell: a document shares at most the tokens
    that it does not hold alone with its component, and a link needs num / (num + den) of both sizes. Who cannot
    reach that with the least size allowed in the cell has no such link, and goes; then fewer tokens are shared by the others."""
    n, own = F.col("n"), F.coalesce("own", F.lit(0).cast("bigint"))
    for _ in range(turns):
        buckets = 16 + (state.agg(F.sum("n").alias("n")).first()["n"] or 0) // 2_000_000
        held = full.select("rep", "tokens").join(_listed(state.drop("n"), listed), "rep").select("cluster", "rep", "known", "tokens")
        owned = held.mapInArrow(tidy(_dealt(buckets)), "bucket bigint, tokens binary, at binary, docs binary").groupBy("bucket").applyInArrow(_owned, "cluster bigint, rep bigint, own bigint")
        owned = written(owned.groupBy("cluster", "rep").agg(F.sum("own").alias("own")), "own-tokens")
        least = state.groupBy("cluster").agg(F.min("n").alias("least"))
        may = (n - own) * (num + den) >= num * (n + F.greatest(F.ceil(n * num / den).cast("bigint"), F.col("least")))
        state = written(state.join(owned, ["cluster", "rep"], "left").join(_listed(least, listed), "cluster").where(may).select("cluster", "rep", "n", "known"), "able")
    return state


def _rest(full: DataFrame, state: DataFrame, early: DataFrame, named: DataFrame, check, shape: str, listed: int) -> DataFrame:
    """Links between the components of a cluster, group by group: documents outside the main one ask the groups that share an early token with theirs.
    Early tokens travel packed, a row a document; to a pair of groups go only the documents that hold one of the tokens it shares."""
    sizes = written(state.groupBy("cluster", "known").agg(F.count("*").alias("docs"), F.sum("n").alias("shingles")), "parts")
    main = sizes.groupBy("cluster").agg(F.max(F.struct("docs", "known")).alias("top"), F.count("*").alias("parts")).where("parts > 1").select("cluster", F.col("top.known").alias("main"))
    # groups: slices of a large component; small components share groups
    many = F.greatest(F.ceil(F.col("docs") / UNIT_DOCS), F.ceil(F.col("shingles") / UNIT_SHINGLES)).cast("bigint")
    small = sizes.where(many == 1).groupBy("cluster").agg(F.greatest(F.ceil(F.sum("docs") / UNIT_DOCS), F.ceil(F.sum("shingles") / UNIT_SHINGLES)).cast("bigint").alias("shared"))
    plan = sizes.withColumn("slices", many).join(small, "cluster", "left").join(main, "cluster")
    lone = F.col("slices") == 1
    group = F.when(lone, F.struct(F.lit(-1).cast("bigint").alias("of"), F.pmod(F.xxhash64("known"), F.col("shared")).alias("part"))).otherwise(F.struct(F.col("known").alias("of"), F.pmod(F.xxhash64("rep"), F.col("slices")).alias("part")))
    gid = F.xxhash64("cluster", "group").alias("gid")
    placed = state.join(plan.select("cluster", "known", "slices", "shared", "main"), ["cluster", "known"]).select("cluster", "rep", "known", group.alias("group"), (F.col("known") != F.col("main")).alias("apart"))
    placed = written(placed.select("cluster", "rep", "known", "apart", gid, F.col("group.of").alias("of")), "placed")
    who = written(named.join(_listed(placed.select("rep").distinct(), listed), "rep"), "placed-named")
    mine = early.join(_listed(who, listed), "doc_id").groupBy("rep").agg(F.array_distinct(F.flatten(F.collect_set("tokens"))).alias("mine"))
    mine = written(mine.join(placed, "rep"), "placed-early")
    held = written(mine.select("cluster", "gid", "of", "apart", F.explode("mine").alias("token")).distinct(), "early-held")
    ask = held.where("apart").select("token", "cluster", F.col("gid").alias("ask"), F.col("of").alias("ask_of")).distinct()
    met = ask.join(held.select("token", "cluster", "gid", "of").distinct(), ["token", "cluster"]).where("ask_of <> of or of = -1")
    pairs = written(met.groupBy("cluster", F.least("ask", "gid").alias("low"), F.greatest("ask", "gid").alias("high")).agg(F.collect_set("token").alias("shared")), "group-pairs")
    sides = pairs.withColumn("gid", F.explode(F.array_distinct(F.array("low", "high"))))
    units = mine.join(sides, ["cluster", "gid"]).where(F.arrays_overlap("mine", "shared")).select("cluster", "low", "high", "rep", "known", F.col("apart").alias("asking"))
    units = written(units, "group-units")
    return written(full.select("rep", "tokens").join(_listed(units, listed), "rep").groupBy("cluster", "low", "high").applyInArrow(check, shape), "links")


def one_of_each(docs: DataFrame, words: int = 5, num: int = 4, den: int = 5, listed: int = 1_000_000) -> DataFrame:
    """The rows of docs, with all their columns, without the near duplicates: of each component the
    document of the least doc_id stays. Of rows alike in doc_id and text one stays; rows of null
    doc_id stay; documents without words are linked with nothing and stay."""
    found = written(jaccard_components(docs, words, num, den), "components")
    gone = found.where(F.col("component_id") != F.col("doc_id")).select("doc_id", "mark").distinct()
    twice = found.where("doc_id is not null").groupBy("doc_id", "mark").agg(F.count("*").alias("rows")).where("rows > 1").select("doc_id", "mark")
    side = F.broadcast(gone) if gone.count() <= listed else gone  # two numbers a row, of checked size
    kept = docs.join(side, (docs["doc_id"] == side["doc_id"]) & (F.xxhash64(docs["text"]) == side["mark"]), "left_anti")
    if twice.isEmpty():
        return kept
    # rows alike in doc_id and text: all but one of them go
    apart = kept.join(twice, (docs["doc_id"] == twice["doc_id"]) & (F.xxhash64(docs["text"]) == twice["mark"]), "left_anti")
    alike = kept.join(twice, (docs["doc_id"] == twice["doc_id"]) & (F.xxhash64(docs["text"]) == twice["mark"]), "left_semi")
    return apart.unionByName(alike.dropDuplicates(["doc_id", "text"]))
