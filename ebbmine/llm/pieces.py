"""SentencePiece encoding and decoding by forward scores shared along common prefixes.

Texts are cut into marked words (a run of word marks with what follows it; no piece of the
vocabulary reaches over such a cut). The distinct words of a block of texts are sorted, which is
the depth-first order of their trie: consecutive words share their common prefix, and the forward
table of that prefix is reused; only the rest of a word is computed.

For a BPE model the forward table holds, for each prefix, the last piece of its encoding. It
depends on the prefix alone: prefix[:i] ends in piece p exactly if the encoding of prefix[:i-len(p)]
ends in a piece q whose join with p encodes to (q, p) again, and just one p does. For a unigram
model it is the usual best-score table. Words with two or more marks in a row have pieces of equal
rank and are merged directly.

Null or empty text: no piece. Characters outside the vocabulary become byte pieces. A mark
character (U+2581) in a text reads as a space, as in the reference library. Rows are never merged
or dropped, repeated or null ids included; extra columns are ignored; texts are encoded whole, in
blocks of `block_chars` characters.
"""

from __future__ import annotations

import heapq
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from pyspark.sql.types import StringType, StructField, StructType

from .common import only, tidy

MARK = "▁"
#: Ranges of a regular expression's class: Latin letters, and ASCII characters that are no letters.
LATIN, SIGNS = "A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f", r"!-@\[-`{-~"
#: Distinct words, and pairs of pieces, remembered by a worker process.
REMEMBERED, PAIRS = 100_000, 300_000


class PieceModel:
    """The vocabulary of a SentencePiece model file with byte fallback."""

    def __init__(self, path: str):
        from sentencepiece import sentencepiece_model_pb2 as proto

        model = proto.ModelProto()
        with open(path, "rb") as f:
            model.ParseFromString(f.read())
        if model.trainer_spec.model_type not in (1, 2) or model.normalizer_spec.name != "identity" or model.normalizer_spec.remove_extra_whitespaces:
            raise ValueError("only unigram or BPE models with the identity normaliser are supported")
        self.bpe = model.trainer_spec.model_type == 2
        self.prefix = model.normalizer_spec.add_dummy_prefix
        self.ids = {p.piece: k for k, p in enumerate(model.pieces) if p.type == 1}
        self.scores = {p.piece: p.score for p in model.pieces if p.type == 1}
        self.bytes = {int(p.piece[3:5], 16): k for k, p in enumerate(model.pieces) if p.type == 6}
        self.unknown = next(k for k, p in enumerate(model.pieces) if p.type == 2)
        back = {k: bytes([b]) for b, k in self.bytes.items()}
        self.surface = [back.get(k, p.piece.replace(MARK, " ").encode() if p.type == 1 else b"") for k, p in enumerate(model.pieces)]
        self.longest = max(len(p) for p in self.ids if MARK * 2 not in p)
        lines = "\n" if not any("\n" in p for p in self.ids) else ""
        whole = rf"{MARK}*[^{MARK}{lines}]+"
        if not any(re.search(rf"[{LATIN}][{SIGNS}]", p) for p in self.ids):
            # no piece goes on after a Latin letter with an ASCII sign or digit: cut there, too
            whole = rf"{MARK}*[^{MARK}{lines}{LATIN}]*[{LATIN}]+(?=[{SIGNS}])|{whole}"
        self.word = re.compile(rf"{whole}|{MARK}+" + (rf"|{lines}" if lines else ""))
        # every ending of a piece: the piece itself if it is one that encodes to itself, else ""
        self.endings = {}
        if self.bpe:
            for p in self.ids:
                for k in range(1, len(p)):
                    self.endings.setdefault(p[k:], "")
            self.endings |= {p: p for p in self.ids if merged(self.scores, p) == [p]}
        if any(MARK in p.lstrip(MARK) for p in self.ids):
            raise ValueError("the vocabulary has pieces across words")


def merged(scores: dict[str, float], word: str) -> list[str]:
    """Byte-pair encoding by its definition: the best adjacent pair, the leftmost of equals, is joined until none is left."""
    part, n = list(word), len(word)
    left, right = list(range(-1, n - 1)), [*range(1, n), -1]
    queue = [(-scores[x], k, x) for k in range(n - 1) if (x := part[k] + part[k + 1]) in scores]
    heapq.heapify(queue)
    while queue:
        _, k, x = heapq.heappop(queue)
        r = right[k]
        if not part[k] or r < 0 or len(part[k]) + len(part[r]) != len(x) or part[k] + part[r] != x:
            continue
        part[k], part[r] = x, ""
        right[k] = right[r]
        if right[r] >= 0:
            left[right[r]] = k
            y = x + part[right[r]]
            if y in scores:
                heapq.heappush(queue, (-scores[y], k, y))
        if left[k] >= 0:
            y = part[left[k]] + x
            if y in scores:
                heapq.heappush(queue, (-scores[y], left[k], y))
    return [x for x in part if x]


class Encoder:
    def __init__(self, model: PieceModel):
        self.model, self.words = model, {}
        self.after: dict[str, dict[str, bool]] = {}  # after[q][p]: whether q and p, joined, encode to (q, p)
        self.pairs = 0

    def _fits(self, known: dict[str, bool], q: str, p: str) -> bool:
        self.pairs += 1
        known[p] = fits = merged(self.model.scores, q + p) == [q, p]
        return fits

    def forward(self, words: list[str]) -> None:
        """Encodes sorted distinct words, walking their trie depth-first."""
        if not self.model.bpe:
            return self._best_scores(words)
        if self.pairs > PAIRS:
            self.after.clear()
            self.pairs = 0
        endings, after, fits, ids = self.model.endings.get, self.after, self._fits, self.model.ids
        last: list[str] = [""]  # last[i]: the last piece of the encoding of the first i characters
        nexts: list[dict] = [{}]  # nexts[i]: what is known of the pieces after it
        before = ""
        for word in words:
            n = len(word)
            same, most = 0, min(n, len(before))
            while same < most and word[same] == before[same]:
                same += 1
            del last[same + 1 :], nexts[same + 1 :]
            for i in range(same + 1, n + 1):
                found = None
                for j in range(i - 1, -1, -1):
                    p = endings(word[j:i])
                    if not p:
                        if j == i - 1:
                            p = word[j]  # a lone character may stand for itself
                        elif p is None:
                            break  # no piece ends like this
                        else:
                            continue
                    if j:
                        known = nexts[j]
                        good = known.get(p)
                        if good if good is not None else fits(known, last[j], p):
                            found = p
                            break
                    else:
                        found = p
                        break
                if found is None:
                    raise AssertionError(f"no last piece for {word[:i]!r}")
                last.append(found)
                known = after.get(found)
                if known is None:
                    known = after[found] = {}
                nexts.append(known)
            before = word
            out, i = [], n
            while i:
                out.append(last[i])
                i -= len(last[i])
            self.words[word] = self._numbers(out[::-1])
        return None

    def _best_scores(self, words: list[str]) -> None:
        ids, scores, longest = self.model.ids, self.model.scores, self.model.longest
        floor = min(scores.values()) - 10.0
        best, last, before = [0.0], [""], ""
        for word in words:
            n = len(word)
            same, most = 0, min(n, len(before))
            while same < most and word[same] == before[same]:
                same += 1
            del best[same + 1 :], last[same + 1 :]
            for i in range(same + 1, n + 1):
                top, piece = best[i - 1] + floor, word[i - 1]
                for j in range(max(0, i - longest), i):
                    p = word[j:i]
                    if p in ids and best[j] + scores[p] > top:
                        top, piece = best[j] + scores[p], p
                best.append(top)
                last.append(piece)
            before, out, i = word, [], n
            while i:
                out.append(last[i])
                i -= len(last[i])
            self.words[word] = self._numbers(out[::-1])

    def _numbers(self, parts: list[str]) -> bytes:
        ids, low, out = self.model.ids, self.model.bytes, []
        for p in parts:
            k = ids.get(p)
            if k is not None:
                out.append(k)
            elif low:
                out += [low[b] for b in p.encode("utf-8", "surrogatepass")]
            else:
                out.append(self.model.unknown)
        return np.array(out, np.int32).tobytes()

    def encode(self, texts: list[str | None], block_chars: int = 1 << 20) -> list[np.ndarray]:
        out, block, size = [], [], 0
        for text in texts:
            marked = (text or "").replace(" ", MARK)
            block.append(MARK + marked if marked and self.model.prefix else marked)
            size += len(marked)
            if size >= block_chars:
                out += self._block(block)
                block, size = [], 0
        return out + self._block(block)

    def _block(self, marked: list[str]) -> list[np.ndarray]:
        if len(self.words) > REMEMBERED:
            self.words.clear()
        cut = self.model.word.findall
        split = [cut(x) for x in marked]
        new = {w for ws in split for w in ws} - self.words.keys()
        runs = {w for w in new if w.startswith(MARK * 2)} if self.model.bpe else set()
        for w in runs:
            self.words[w] = self._numbers(merged(self.model.scores, w))
        self.forward(sorted(new - runs))
        get = self.words.__getitem__
        return [np.frombuffer(b"".join(map(get, ws)), np.int32) for ws in split]


def decoded(model: PieceModel, ids) -> str:
    surface = model.surface
    text = b"".join([surface[k] for k in ids]).decode("utf-8", "replace")
    return text[1:] if model.prefix and text.startswith(" ") else text


def encode_texts(docs: DataFrame, model: PieceModel, verify: bool = False) -> DataFrame:
    """docs(doc_id, text) -> doc_id, text, ids array<int>; with verify also round_trip: whether the
    decoded ids give the text again (read with spaces for marks), found in the same pass."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # a vocabulary, of fixed size

    def run(batches):
        model = sent.value
        encoder = model.encoder = getattr(model, "encoder", None) or Encoder(model)  # kept by the worker for its next tasks
        for batch in batches:
            at = 0
            texts = batch.column("text")
            while at < batch.num_rows:  # slices of bounded size, whatever the texts' lengths
                rows, chars = 0, 0
                while at + rows < batch.num_rows and rows < 1000 and (chars < 2 << 20 or not rows):
                    chars += len(texts[at + rows].as_buffer()) if texts[at + rows].is_valid else 0
                    rows += 1
                part = batch.slice(at, rows)
                ids = encoder.encode(part.column("text").to_pylist())
                offsets = np.zeros(rows + 1, np.int32)
                np.cumsum([len(x) for x in ids], out=offsets[1:])
                flat = np.concatenate(ids) if ids else np.empty(0, np.int32)
                lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat, pa.int32()))
                out = pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text"), lists], ["doc_id", "text", "ids"])
                if verify:
                    same = [decoded(model, x.tolist()) == (t or "").replace(MARK, " ") for x, t in zip(ids, part.column("text").to_pylist())]
                    out = out.append_column("round_trip", pa.array(same))
                yield out
                at += rows

    shape = "doc_id bigint, text string, ids array<int>" + ", round_trip boolean" * verify
    return only(docs, doc_id="bigint", text="string").mapInArrow(tidy(run), shape)


def decode_ids(encoded: DataFrame, model: PieceModel) -> DataFrame:
    """encoded(..., ids) -> the same with decoded: the text of the ids (empty for none or null)."""
    sent = encoded.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            ids = batch.column("ids")
            texts = [decoded(sent.value, x.values.to_numpy(zero_copy_only=False).tolist()) if x.is_valid else "" for x in ids]
            yield batch.append_column("decoded", pa.array(texts, pa.string()))

    return encoded.mapInArrow(tidy(run), StructType([*encoded.schema.fields, StructField("decoded", StringType())]))
