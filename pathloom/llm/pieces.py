"""Sampled SentencePiece segmentations and lossless decoding.

The piece lattice of a text falls apart at word starts, since no piece goes on across one. Words
are filtered forward: the mass of all ways to spell a word's first i characters. That mass depends on those
characters only, so words that begin alike share it. A segmentation is then drawn backward from its end, each step choosing the last piece in proportion to
its share of that mass. Draws come from a counter hashed with the row's key, the word's number and the step,
so they depend on nothing but the row. All words of a batch are walked back together.

A piece's weight is 1 / rank to the power theta, by the model's merge priority. Characters outside the
vocabulary, and the word mark itself where a text has it, are spelled by byte pieces, so decoding
gives back every text.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import pick, table
from .memory import released

#: The model's mark for a space.
MARK = "\u2581"
#: Among words, a literal mark in the text. No word looks like it.
LITERAL = "\n\n"
THETA = 1.0
SEED = 11
#: Word beginnings that a worker keeps, and bytes of text walked back at once.
MOST_NODES, BATCH_CHARS = 1_000_000, 2 << 20
#: Every character's factor in a spelling's weight. The same for all spellings of a word, it keeps masses in range.
LEVEL, LONG = 30.0, 64
#: Bits of an edge's place within its node's mass, in the tables that draws are looked up in.
SHARE_BITS = 33
#: Weight of spelling a character by bytes, as of a piece of this rank.
BYTE_RANK = 64_000


class PieceSampler:
    def __init__(self, path: str, theta: float = THETA, most_nodes: int = MOST_NODES):
        import sentencepiece

        self.most_nodes = most_nodes
        model = sentencepiece.SentencePieceProcessor(model_file=path)
        size = model.get_piece_size()
        plain = [i for i in range(size) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i))]
        pieces = {model.id_to_piece(i): i for i in plain}
        if any(MARK in p.lstrip(MARK) for p in pieces) or any("\n" in p and p != "\n" for p in pieces):
            raise ValueError("a piece goes on across a word start")
        self.bytes = {int(model.id_to_piece(i)[3:5], 16): i for i in range(size) if model.is_byte(i)}
        if len(self.bytes) != 256:
            raise ValueError("the model has no byte pieces")
        #: ends of pieces: how a piece's characters stop, with the piece and its weight if it is one
        self.ends: dict[str, tuple[int, float] | None] = {}
        for p, i in pieces.items():
            for k in range(1, len(p)):
                self.ends.setdefault(p[k:], None)
            self.ends[p] = (i, max(1.0, 1.0 - model.get_score(i)) ** -theta * LEVEL ** len(p))
        self.byte_weight = BYTE_RANK**-theta * LEVEL
        self.text = [b""] * size
        for p, i in pieces.items():
            self.text[i] = p.replace(MARK, " ").encode()
        for b, i in self.bytes.items():
            self.text[i] = bytes([b])
        self.size = size
        self.find = re.compile(f"\n|{MARK}*[^{MARK}\n]+|{MARK}+").findall
        self.spelled: dict[str, int] = {}  # characters spelled by bytes: codes from size on
        self.spellings: list[list[int]] = []
        self.forget()

    def forget(self) -> None:
        """Drop all word beginnings; results do not depend on what is kept."""
        self.base: dict[str, int] = {}
        # node 0 is the start of every word; above: the node of the beginning that is one character shorter
        self.mass: list[float] = [1.0]
        self.above: list[int] = [0]
        self.edges = (np.empty(1 << 16, np.uint64), np.empty(1 << 16, np.int32), np.empty(1 << 16, np.int32))
        self.filled = 0
        self._refresh()

    def _refresh(self) -> None:
        """Empty the lists of new edges (running mass, node where they start, piece) and of new nodes (mass, number of edges, node)."""
        self.running: list[float] = []
        self.origin: list[int] = []
        self.piece: list[int] = []
        self.totals: list[float] = []
        self.counts: list[int] = []
        self.first = len(self.mass)

    def _spelling(self, c: str) -> int:
        """The code of a character spelled by bytes: the byte piece, or one from size on for several."""
        if c not in self.spelled:
            ids = [self.bytes[b] for b in c.encode("utf-8", "surrogatepass")]
            self.spelled[c] = ids[0] if len(ids) == 1 else self.size + len(self.spellings)
            if len(ids) > 1:
                self.spellings.append(ids)
        return self.spelled[c]

    def _edge(self, running: float, origin: int, piece: int) -> None:
        self.running.append(running)
        self.origin.append(origin)
        self.piece.append(piece)

    def _node(self, total: float, edges: int, above: int) -> int:
        """A new node where the last edges made end."""
        self.totals.append(total)
        self.counts.append(edges)
        self.mass.append(total)
        self.above.append(above)
        return len(self.mass) - 1

    def _add(self, word: str) -> int:
        """Filter a word forward; the number of its end node."""
        if word == LITERAL:
            self._edge(1.0, 0, self._spelling(MARK))
            self.base[word] = node = self._node(1.0, 1, 0)
            return node
        n = len(word)
        if n > LONG:
            return self._add_long(word)
        base, end, mass, above = self.base, self.ends.get, self.mass, self.above
        add_running, add_origin, add_piece = self.running.append, self.origin.append, self.piece.append
        last = 0
        for e in range(n - 1, 0, -1):
            if last := base.get(word[:e], 0):
                break
        else:
            e = 0
        for e in range(e + 1, n + 1):
            total, at, before = 0.0, last, len(self.origin)
            for s in range(e - 1, -1, -1):
                found = end(word[s:e], 0)
                if found:
                    total += found[1] * mass[at]
                    add_running(total)
                    add_origin(at)
                    add_piece(found[0])
                elif found == 0:
                    break
                at = above[at]
            if not end(word[e - 1]):
                total += self.byte_weight * mass[last]
                self._edge(total, last, self._spelling(word[e - 1]))
            base[word[:e]] = last = self._node(total, len(self.origin) - before, last)
        return last

    def _add_long(self, word: str) -> int:
        """As _add, for a word of any length: nodes of its own, masses kept in range as they come."""
        scaled, nodes = [1.0], [0]
        for e in range(1, len(word) + 1):
            total, before = 0.0, len(self.origin)
            for s in range(e - 1, -1, -1):
                found = self.ends.get(word[s:e], 0)
                if found:
                    total += found[1] * scaled[s]
                    self._edge(total, nodes[s], found[0])
                elif found == 0:
                    break
            if not self.ends.get(word[e - 1]):
                total += self.byte_weight * scaled[e - 1]
                self._edge(total, nodes[e - 1], self._spelling(word[e - 1]))
            nodes.append(self._node(total, len(self.origin) - before, 0))
            scaled.append(total)
            if not 1e-60 < total < 1e60:  # only proportions within reach of a piece matter
                scaled[-40:] = [x / total for x in scaled[-40:]]
        self.base[word] = nodes[-1]
        return nodes[-1]

    def _tables(self) -> tuple[np.ndarray, ...]:
        """Of all edges, by node: the node's number above the share of its mass up to the edge, where the edge starts, its piece.

        Number and share have bits of their own, so a share does not depend on which number a node got.
        """
        counts = np.array(self.counts, np.int64)
        share = np.array(self.running) / np.repeat(np.array(self.totals), counts)
        number = np.repeat(np.arange(self.first, len(self.mass), dtype=np.uint64), counts)
        share = (number << np.uint64(SHARE_BITS)) + np.rint(share * (1 << SHARE_BITS)).astype(np.uint64)
        to = self.filled + len(share)
        if to > len(self.edges[0]):
            self.edges = tuple(np.concatenate([x[: self.filled], np.empty(to, x.dtype)]) for x in self.edges)
        for x, new in zip(self.edges, (share, self.origin, self.piece), strict=True):
            x[self.filled : to] = new
        self.filled = to
        self._refresh()
        return tuple(x[:to] for x in self.edges)

    def sample(self, texts: list[str | None], seeds: list[int]) -> list[np.ndarray]:
        """Piece ids of one drawn segmentation of each text."""
        if len(self.mass) > self.most_nodes:
            self.forget()
        ends: list[int] = []
        counts = []
        get, add = self.base.get, self._add
        for t in texts:
            if not t:
                counts.append(0)
                continue
            if MARK in t:
                words = self._around_marks(t)
            else:
                words = self.find(MARK + t.replace(" ", MARK))
            counts.append(len(words))
            ends.extend([add(w) if (e := get(w)) is None else e for w in words])
        if not ends:
            return [np.empty(0, np.int32) for _ in texts]
        top, origin, piece = self._tables()
        node = np.array(ends, np.int64)
        counts = np.array(counts)
        number = np.arange(len(node)) - np.repeat(np.cumsum(counts) - counts, counts)
        state = np.repeat(np.array(seeds, np.uint64), counts) + number.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        steps, live = [], np.arange(len(node))
        length = np.zeros(len(node), np.int32)
        while len(live):
            u = _uniform(state[live], len(steps))
            edge = np.searchsorted(top, (node[live].astype(np.uint64) << np.uint64(SHARE_BITS)) + u, "right")
            steps.append((live, piece[edge]))
            length[live] += 1
            node[live] = origin[edge]
            live = live[node[live] > 0]
        at = np.cumsum(length)
        out = np.empty(int(at[-1]), np.int32)
        for k, (which, ids) in enumerate(steps):
            out[at[which] - 1 - k] = ids
        bounds = np.concatenate([[0], at])[np.concatenate([[0], np.cumsum(counts)])]
        rows = [out[i:j] for i, j in zip(bounds[:-1], bounds[1:], strict=True)]
        if self.spellings and (out >= self.size).any():
            rows = [self._spelled_out(r) if (r >= self.size).any() else r for r in rows]
        return rows

    def _around_marks(self, t: str) -> list[str]:
        """The words of a text that has the mark itself in it."""
        words: list[str] = []
        for i, stretch in enumerate(t.split(MARK)):
            if i:
                words.append(LITERAL)
            words.extend(self.find(("" if i else MARK) + stretch.replace(" ", MARK)))
        return words

    def _spelled_out(self, ids: np.ndarray) -> np.ndarray:
        out: list[int] = []
        for i in ids.tolist():
            if i < self.size:
                out.append(i)
            else:
                out.extend(self.spellings[i - self.size])
        return np.array(out, np.int32)

    def decode(self, ids) -> str:
        """The text of which ids are a segmentation."""
        data = b"".join([self.text[i] for i in ids])
        return data[1:].decode("utf-8", "surrogatepass")


def _uniform(state: np.ndarray, step: int) -> np.ndarray:
    """Numbers of SHARE_BITS bits from hashed counters."""
    z = state + np.uint64(((step + 1) * 0xD1342543DE82EF95) % (1 << 64))
    z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return (z ^ (z >> np.uint64(31))) >> np.uint64(64 - SHARE_BITS)


@lru_cache(maxsize=2)
def sampler(path: str, theta: float, most_nodes: int = MOST_NODES) -> PieceSampler:
    """One sampler per Python worker."""
    return PieceSampler(path, theta, most_nodes)


def _row_seed(key, text: str | None, seed: int) -> int:
    return xxhash.xxh3_64_intdigest(f"k{key}" if key is not None else f"t{text}", seed)


def _portions(batch: pa.RecordBatch) -> Iterator[tuple[list, list]]:
    """Keys and texts of a batch, some rows at a time."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column("text")), 0).to_numpy(zero_copy_only=False))
    at = 0
    while at < batch.num_rows:
        base = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, base + BATCH_CHARS, "right")))
        part = batch.slice(at, to - at)
        yield part.column("key").to_pylist(), part.column("text").to_pylist()
        at = to


def _sampled(path: str, theta: float, seed: int, ids: bool, most_nodes: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = sampler(path, theta, most_nodes)
        try:
            yield from draw(model, batches)
        finally:
            model.forget()  # the worker goes on to other stages

    def draw(model: PieceSampler, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for keys, texts in _portions(batch):
                rows = model.sample(texts, [_row_seed(k, t, seed) for k, t in zip(keys, texts, strict=True)])
                counts = pa.array(list(map(len, rows)), pa.int64())
                if ids:
                    ends = np.concatenate([[0], np.cumsum(counts)]).astype(np.int32)
                    found = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([*rows, np.empty(0, np.int32)]).astype(np.int32)))
                    yield pa.RecordBatch.from_arrays([pa.array(keys, batch.schema.field("key").type), counts, found], names=["key", "n_pieces", "pieces"])
                else:
                    digests = [hashlib.sha256(r.astype("<i4").tobytes()).hexdigest() for r in rows]
                    back = [model.decode(r.tolist()) == (t or "") for r, t in zip(rows, texts, strict=True)]
                    yield pa.RecordBatch.from_arrays([pa.array(keys, batch.schema.field("key").type), counts, pa.array(digests), pa.array(back)], names=["key", "n_pieces", "pieces_sha256", "lossless"])

    return run


def sampled_pieces(docs: DataFrame, model_path: str, theta: float = THETA, seed: int = SEED, key: str = "doc_id", text: str = "text", ids: bool = True, most_nodes: int = MOST_NODES) -> DataFrame:
    """key, n_pieces, pieces (ids) of one drawn segmentation of each row's text.

    With ids=False the ids stay in the worker: pieces_sha256 is the digest of their little-endian 32-bit
    form and lossless says whether decoding them gave the text back. Null and empty texts have no
    pieces. Rows with equal key and text get equal pieces; rows with a null key are seeded by their
    text. Extra columns are ignored; nothing is shuffled. most_nodes bounds a worker's memory and has no
    influence on results.
    """
    rows = pick(docs, key, text).toDF("key", "text")
    kind = rows.schema["key"].dataType.simpleString()
    columns = "pieces array<int>" if ids else "pieces_sha256 string, lossless boolean"
    return rows.mapInArrow(released(_sampled(model_path, theta, seed, ids, most_nodes)), f"key {kind}, n_pieces long, {columns}").withColumnRenamed("key", key)


def decoded(rows: DataFrame, model_path: str, pieces: str = "pieces", text: str = "text") -> DataFrame:
    """rows with the text that their pieces spell; null pieces give a null text."""

    @F.pandas_udf("string")
    def decode(found):
        import pandas as pd

        model = sampler(model_path, THETA)
        return pd.Series([None if x is None else model.decode(x) for x in found], dtype=object)

    return rows.withColumn(text, decode(pieces))


def op2_lattice_sampled_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return sampled_pieces(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))
