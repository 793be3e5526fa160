"""Vector bin packing of token pieces under limits on tokens, segments and loss-bearing tokens.

A task keeps a bounded pool of pieces. For the open sequence it takes the
piece whose demand has the largest dot product with the room left, both scaled
by the limits; if no whole piece fits, the best one is cut where the sequence
ends. Tasks share nothing, so there is no shuffle, and a lost task is repeated
on its own.
"""

from __future__ import annotations

import functools
import itertools
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .workers import tidy

#: Pieces among which the heuristic chooses; words whose ids a task remembers.
POOL, WORD_MEMORY = 256, 2_000_000


@dataclass(frozen=True)
class Limits:
    """Of one sequence. ``power_tail``: the last pool is cut to lengths that are powers of two and need no padding."""

    tokens: int = 2048
    segments: int = 2048
    loss_tokens: int = 2048
    power_tail: bool = True


@dataclass
class Piece:
    """Tokens [start, stop) of a document, all or none of them loss-bearing."""

    doc: int
    start: int
    stop: int
    loss: bool = True


class DotProductPacker:
    """Yields sequences, each a list of pieces; pieces may be cut anywhere."""

    def __init__(self, limits: Limits, pool: int = POOL):
        self.limits, self.size = limits, pool
        self.pieces: list[Piece] = []
        self.demand = np.zeros((0, 3))

    def add(self, pieces: list[Piece]) -> Iterator[list[Piece]]:
        fresh = []
        for piece in pieces:
            most = min(self.limits.tokens, self.limits.loss_tokens) if piece.loss else self.limits.tokens
            while piece.stop - piece.start >= most:
                yield [Piece(piece.doc, piece.start, piece.start + most, piece.loss)]
                piece = Piece(piece.doc, piece.start + most, piece.stop, piece.loss)
            if piece.stop > piece.start:
                fresh.append(piece)
        self._extend(fresh)
        while len(self.pieces) > self.size:
            yield self._fill(self.limits.tokens)

    def close(self) -> Iterator[list[Piece]]:
        while self.pieces:
            left = int(self.demand[:, 0].sum())
            if self.limits.power_tail and left < self.limits.tokens:
                yield self._fill(1 << (left.bit_length() - 1))
            else:
                yield self._fill(self.limits.tokens)

    def _extend(self, pieces: list[Piece]) -> None:
        if pieces:
            self.pieces += pieces
            rows = np.array([(p.stop - p.start, 1, (p.stop - p.start) * p.loss) for p in pieces], float)
            self.demand = np.concatenate([self.demand, rows])

    def _fill(self, tokens: int) -> list[Piece]:
        limit = np.array([tokens, self.limits.segments, min(tokens, self.limits.loss_tokens)], float)
        room, taken, used = limit.copy(), [], np.zeros(len(self.pieces), bool)
        fits = np.ones(len(self.pieces), bool)
        scaled = self.demand / np.maximum(limit, 1) ** 2
        while room[0] > 0 and room[1] > 0:
            fits &= (self.demand <= room).all(1) & ~used
            if fits.any():
                k = int(np.argmax(np.where(fits, scaled @ room, -1)))
                taken.append(self.pieces[k])
                room -= self.demand[k]
                used[k] = True
                continue
            score = np.where(used, -1, scaled @ room)
            score[(self.demand[:, 2] > 0) & (room[2] <= 0)] = -1
            k = int(np.argmax(score)) if len(score) else 0
            if not len(score) or score[k] < 0:
                break
            piece = self.pieces[k]
            n = int(min(room[0], room[2]) if piece.loss else room[0])
            taken.append(Piece(piece.doc, piece.start, piece.start + n, piece.loss))
            room -= (n, 1, n * piece.loss)
            piece.start += n
            self.demand[k] -= (n, 0, n * piece.loss)
        self.pieces = [p for p, gone in zip(self.pieces, used, strict=True) if not gone]
        self.demand = self.demand[~used]
        return taken


@functools.lru_cache(2)
def _loaded(path: str) -> tuple:
    """The tokenizer of a file, and which of its ids end a word; kept by the worker."""
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    vocabulary = tokenizer.get_vocab()
    ends = np.zeros(max(vocabulary.values()) + 1, bool)
    ends[[k for token, k in vocabulary.items() if token.endswith("</w>")]] = True
    return tokenizer, ends


def _words(text: bytes) -> list[bytes]:
    """What white space parts, lower-cased as the tokenizer does itself, so fewer words differ; names of its special tokens stay as they stand."""
    return text.split() if b"<|" in text else text.lower().split()


class WordTokenizer:
    """Ids of whole texts from the ids of their words, remembered by word.

    Exact for tokenizers that treat what white space parts independently of
    each other, as the lower-casing word-end vocabulary does.
    """

    def __init__(self, path: str, memory: int = WORD_MEMORY):
        (self.tokenizer, self.ends_word), self.memory = _loaded(path), memory
        self._clear()

    def _clear(self) -> None:
        self.known: dict[bytes, int] = {}
        self.flat, self.filled = np.empty(1 << 16, np.uint32), 0
        self.begin, self.count, self.uses = np.empty(1 << 14, np.int64), np.empty(1 << 14, np.int32), np.zeros(1 << 14, np.int32)

    def _forget(self) -> None:
        """Keeps the words that came up in two slices of texts or more; most others never come again."""
        kept = [(word, k) for word, k in self.known.items() if self.uses[k] > 1]
        if len(kept) > self.memory // 2:
            kept = []
        ids = [self.flat[self.begin[k] : self.begin[k] + self.count[k]] for _, k in kept]
        uses = self.uses[[k for _, k in kept]]
        self._clear()
        if kept:
            self._remember([word for word, _ in kept], np.concatenate(ids), np.fromiter(map(len, ids), np.int32, len(ids)))
            self.uses[: len(uses)] = uses

    def _encode(self, words: list[str]) -> list[list[int]]:
        return [x.ids for x in self.tokenizer.encode_batch_fast(words, add_special_tokens=False)]

    def _remember(self, words: list[bytes], ids: np.ndarray, counts: np.ndarray) -> None:
        n = len(self.known)
        while n + len(words) > len(self.begin):
            self.begin, self.count, self.uses = (np.resize(x, 2 * len(x)) for x in (self.begin, self.count, self.uses))
        self.uses[n : n + len(words)] = 0
        while self.filled + len(ids) > len(self.flat):
            self.flat = np.resize(self.flat, 2 * len(self.flat))
        self.flat[self.filled : self.filled + len(ids)] = ids
        self.begin[n : n + len(words)] = self.filled + np.cumsum(counts, dtype=np.int64) - counts
        self.count[n : n + len(words)] = counts
        self.filled += len(ids)
        self.known.update(zip(words, range(n, n + len(words)), strict=True))

    def _learn(self, words: list[bytes]) -> None:
        """Plain words go many to a text, as their ends show in the ids; others go one by one."""
        names = b"\n".join(words).decode("utf-8", "replace").split("\n")
        alpha = list(map(str.isalpha, names))
        rest = [(raw, name) for raw, name, plain in zip(words, names, alpha, strict=True) if not plain]
        marked = [x for x in rest if x[1][-1] in ".,!?;:%$#*&" and x[1][:-1].isalpha()]
        other = [x for x in rest if not (x[1][-1] in ".,!?;:%$#*&" and x[1][:-1].isalpha())]
        groups = ((list(itertools.compress(words, alpha)), list(itertools.compress(names, alpha)), 1), ([raw for raw, _ in marked], [name for _, name in marked], 2))
        for raws, spelled, parts in groups:
            for k in range(0, len(raws), 2_048):
                chunk = spelled[k : k + 2_048]
                ids = np.array(self._encode([" ".join(chunk)])[0], np.uint32)
                ends = np.nonzero(self.ends_word[ids])[0]
                if len(ends) == parts * len(chunk) and ends[-1] == len(ids) - 1:
                    self._remember(raws[k : k + 2_048], ids, np.diff(ends[parts - 1 :: parts] + 1, prepend=0).astype(np.int32))
                else:
                    other += zip(raws[k : k + 2_048], chunk, strict=True)
        for k in range(0, len(other), 8_192):
            chunk = other[k : k + 8_192]
            found = self._encode([w for _, w in chunk])
            counts = np.fromiter(map(len, found), np.int32, len(found))
            self._remember([raw for raw, _ in chunk], np.fromiter(itertools.chain.from_iterable(found), np.uint32, int(counts.sum())), counts)

    def ids(self, texts: list[bytes]) -> list[np.ndarray]:
        words = [_words(t) for t in texts]
        if len(self.known) > self.memory:
            self._forget()
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        every = list(itertools.chain.from_iterable(words))
        at = np.fromiter(map(self.known.get, every, itertools.repeat(-1)), np.int32, len(every))
        missing = np.nonzero(at < 0)[0]
        if len(missing):
            lost = [every[k] for k in missing.tolist()]
            self._learn(list(dict.fromkeys(lost)))
            at[missing] = np.fromiter(map(self.known.__getitem__, lost), np.int32, len(lost))
        seen = np.zeros(len(self.uses), np.int32)
        seen[at] = 1
        self.uses += seen
        count, begin = self.count[at], self.begin[at]
        ends = np.cumsum(count, dtype=np.int64)
        total = int(ends[-1]) if len(ends) else 0
        spots = np.repeat((begin - ends + count), count)
        spots += np.arange(total)
        flat = self.flat[spots]
        cuts = np.concatenate([[0], ends])[np.cumsum(sizes)]
        return np.split(flat, cuts[:-1])


@functools.lru_cache(1)
def _kept(path: str) -> WordTokenizer:
    """One tokenizer with its words for all tasks of a worker."""
    return WordTokenizer(path)


def pack_documents(docs: DataFrame, tokenizer_path: str, end_id: int = 1, limits: Limits = Limits(), id_col: str = "doc_id", text_col: str = "text", loss_col: str | None = None, with_ids: bool = True, keep_words: bool = True) -> DataFrame:
    """One row per piece: where it lies in its document and in its sequence.

    Columns ``doc_id, start, length, ids_crc32, doc_tokens, sequence_id,
    offset, sequence_tokens, loss_tokens`` and, unless left out, ``ids``. A null or blank text is its
    end id alone; a text of any length is cut into as many pieces as needed;
    repeated rows are packed as often as they come (their pieces share a
    doc_id). ``loss_col`` is a boolean: does the row bear loss; null counts as
    true. An empty table gives no pieces. Other columns are not looked at.

    Texts are tokenized in slices of about 4 MB, so memory is bounded by the
    longest text, the pool and the words remembered: 2,000,000 a worker, kept
    from task to task if ``keep_words``, or those of one task.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    loss = F.coalesce(F.col(loss_col).cast("boolean"), F.lit(True)) if loss_col else F.lit(True)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer, packer = (_kept if keep_words else WordTokenizer)(tokenizer_path), DotProductPacker(limits)
        waiting: dict[int, list] = {}  # row: id, ids, tokens not yet placed
        first, rows = TaskContext.get().partitionId() << 36, itertools.count()
        sequence = itertools.count(first)
        out: list[tuple] = []

        def place(sequences: Iterator[list[Piece]]) -> None:
            for pieces in sequences:
                number, offset = next(sequence), 0
                total = sum(p.stop - p.start for p in pieces)
                for p in pieces:
                    doc, ids = waiting[p.doc][:2]
                    part = ids[p.start : p.stop]
                    out.append((doc, p.start, p.stop - p.start, zlib.crc32(part), len(ids), number, offset, total, (p.stop - p.start) * p.loss, part))
                    offset += p.stop - p.start
                    waiting[p.doc][2] -= p.stop - p.start
                    if not waiting[p.doc][2]:
                        del waiting[p.doc]

        def emit() -> pa.RecordBatch:
            columns = list(zip(*out, strict=True)) or [()] * 10
            out.clear()
            arrays = [pa.array(c, t) for c, t in zip(columns, [t for t in fields.values() if t], strict=False)]
            if with_ids:
                flat = np.concatenate(columns[-1]).astype(np.int32) if columns[-1] else np.empty(0, np.int32)
                ends = np.concatenate([[0], np.cumsum(columns[2])]).astype(np.int32)
                arrays.append(pa.ListArray.from_arrays(pa.array(ends), pa.array(flat)))
            return pa.RecordBatch.from_arrays(arrays, list(fields)[: len(arrays)])

        fields: dict[str, pa.DataType | None] = {}
        for batch in batches:
            fields = fields or {"doc_id": batch.column(0).type} | dict.fromkeys(("start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "sequence_tokens", "loss_tokens"), pa.int64()) | {"ids": None}
            ids, bears = batch.column(0).to_pylist(), batch.column(2).to_pylist()
            texts = batch.column(1).cast(pa.binary())
            k = 0
            while k < len(ids):
                part, held = [], 0
                while k + len(part) < len(ids) and held < 4_000_000:
                    part.append(texts[k + len(part)].as_py() or b"")
                    held += len(part[-1])
                pieces = []
                for j, found in enumerate(tokenizer.ids(part)):
                    found = np.append(found, np.uint32(end_id))
                    row = next(rows)
                    waiting[row] = [ids[k + j], found, len(found)]
                    pieces.append(Piece(row, 0, len(found), bears[k + j]))
                k += len(part)
                place(packer.add(pieces))
                yield emit()
        if fields:
            place(packer.close())
            yield emit()

    schema = f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, sequence_tokens long, loss_tokens long" + ", ids array<int>" * with_ids
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"), loss.alias("bears_loss")).mapInArrow(tidy(run), schema)


def vocabulary_path() -> str:
    """Of the public vocabulary with word ends; never copied, read where it is installed."""
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op2_packing(spark, sf_dir: str) -> DataFrame:
    """All documents in sequences of 2,048 tokens; one row per piece, without its ids."""
    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"), vocabulary_path(), with_ids=False)
