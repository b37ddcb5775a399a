"""Token counts by a compiled finite-state transducer.

A byte-level BPE vocabulary is compiled, lazily, into a deterministic transducer over bytes. A state
stands for everything about the bytes read so far that can still matter: the trie nodes of the
vocabulary in which a token could yet end, each with the last token of the encoding before it. A
transition carries how much the number of tokens of the prefix changes (it may be negative: a longer
token can replace several). The count of a pre-token is the sum along its path; whole pre-tokens
are remembered as macro transitions.

At some places the pre-tokeniser always cuts, whatever came before: before white space that follows something
else, and where a run of letters or of digits ends. There the transducer is in its start state, so the state map of
a chunk of text (how any state before it goes over into the state after it, and how many tokens that adds)
needs only what precedes its first such place, the count between the first and the last, and what follows the
last. These maps form a monoid. Long texts are cut into chunks, which are rows of their own and are mapped
independently; neighbouring maps are then composed, FAN at a time, until each text has one. No chunk waits
for another's result, and no task sees more than FAN maps of a text.
"""

from __future__ import annotations

import json
import re
import sys
import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from .common import broadcast_if_small, pick, stored, table

CHUNK_CHARS = 1 << 16
#: Neighbouring maps that are composed at once.
FAN = 64
#: Memo sizes at which the compiled tables of a worker start anew; they bound memory, not results.
MOST_WORDS, MOST_STATES = 600_000, 180_000
#: The token limit that over_limit is about.
LIMIT = 1024
#: The white space of Unicode, and English clitics that are pre-tokens of their own.
WHITE = "\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
CLITICS = "'s|'t|'re|'ve|'m|'ll|'d"


def _class(kind: str) -> str:
    """The ranges, inside a bracketed set, of all code points whose category starts with kind."""
    out, start = [], None
    for i in range(sys.maxunicode + 2):
        inside = i <= sys.maxunicode and unicodedata.category(chr(i))[0] == kind
        if inside and start is None:
            start = i
        elif not inside and start is not None:
            out.append(re.escape(chr(start)) + ("-" + re.escape(chr(i - 1)) if i - 1 > start else ""))
            start = None
    return "".join(out)


def _byte_letters() -> dict[str, int]:
    """The printable stand-in of each byte in byte-level vocabularies: itself if visible in Latin-1, else the next free code point from 256."""
    visible = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in visible]
    return {chr(b): b for b in visible} | {chr(256 + i): b for i, b in enumerate(hidden)}


class BpeTransducer:
    """Counts tokens of pre-tokens; ids, merges and special strings come from a tokenizers JSON file."""

    def __init__(self, spec: dict):
        kind = spec["pre_tokenizer"] or {}
        if spec["model"]["type"] != "BPE" or kind.get("type") != "ByteLevel" or kind.get("add_prefix_space") or not kind.get("use_regex", True) or spec.get("normalizer"):
            raise ValueError("only byte-level BPE without normaliser and prefix space is compiled")
        letters = _byte_letters()
        raw = lambda s: bytes(letters[c] for c in s)
        pairs = (m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"])
        self.rank = {(raw(a), raw(b)): i for i, (a, b) in enumerate(pairs)}
        self.made: dict[bytes, tuple[int, bytes, bytes]] = {}
        for (a, b), i in self.rank.items():
            self.made.setdefault(a + b, (i, a, b))
        self.special = [t["content"] for t in spec.get("added_tokens", [])]
        self.cut = re.compile("|".join(re.escape(s) for s in sorted(self.special, key=len, reverse=True))) if self.special else None
        word, number = _class("L"), _class("N")
        self.find = re.compile(
            f" ?[{word}]+|{CLITICS}| ?[{number}]+| ?[^{WHITE}{word}{number}]+|[{WHITE}]+(?![^{WHITE}])|[{WHITE}]+"
        ).findall
        self.sync = re.compile(f"(?<=[^{WHITE}])(?=[{WHITE}])|(?<=[{word}])(?=[^{word}{WHITE}])|(?<=[{number}])(?=[^{number}{WHITE}])")
        # pairs of characters inside special strings, which no cut may separate
        self.whole = {s[i : i + 2] for s in self.special for i in range(len(s) - 1)}
        self.trie: list[tuple[dict[int, int], bytes | None]] = [({}, None)]
        for token in (raw(s) for s in spec["model"]["vocab"]):
            self._add(token)
        self.fits: dict[tuple[bytes, bytes], bool] = {}
        self._restart()
        outer = self

        class Words(dict):
            def __missing__(self, w: str) -> int:
                if len(self) >= MOST_WORDS:
                    self.clear()
                n = outer.run(w.encode("utf-8", "surrogatepass"))
                self[w] = n
                return n

        self.words = Words()

    def _add(self, token: bytes) -> None:
        at = 0
        for b in token:
            below = self.trie[at][0]
            if b not in below:
                self.trie.append(({}, None))
                below[b] = len(self.trie) - 1
            at = below[b]
        self.trie[at] = (self.trie[at][0], token)

    def _restart(self) -> None:
        # a state is a flat tuple of (trie node, token before it or None, tokens up to there less those of the whole)
        start = (0, None, 0)
        self.states, self.number = [start], {start: 0}
        self.steps: dict[int, int] = {}  # state * 256 + byte: next state * 1024 + 512 + change of the count

    def _spine(self, token: bytes, side: int) -> list[tuple[bytes, int]]:
        """The parts that stand at one end of a token (1: right, 0: left) while it is merged, each with the rank of the merge that takes it up."""
        out, until = [], 1 << 60
        while True:
            out.append((token, until))
            if token not in self.made:
                return out
            until, *parts = self.made[token]
            token = parts[side]

    def _meet(self, a: bytes | None, b: bytes) -> bool:
        """May token b follow token a in an encoding: no merge across their border comes before the merges that take up its two parts."""
        if a is None:
            return True
        if (a, b) not in self.fits:
            if len(self.fits) > MOST_WORDS:
                self.fits.clear()
            rank = self.rank.get
            self.fits[a, b] = not any(
                (r := rank((x, y))) is not None and r < gone and r <= left
                for x, gone in self._spine(a, 1)
                for y, left in self._spine(b, 0)
            )
        return self.fits[a, b]

    def _step(self, state: int, byte: int) -> int:
        """Build the transition of a state on a byte."""
        live, token, delta = [], None, 0
        parts = iter(self.states[state])
        for node, last, rel in zip(parts, parts, parts, strict=True):
            below = self.trie[node][0].get(byte)
            if below is None:
                continue
            children, ended = self.trie[below]
            if ended is not None and token is None and self._meet(last, ended):
                token, delta = ended, rel + 1
            if children:
                live.append((below, last, rel))
        new = (*(x for n, last, rel in live for x in (n, last, rel - delta)), 0, token, 0)
        to = self.number.get(new)
        if to is None:
            self.number[new] = to = len(self.states)
            self.states.append(new)
        self.steps[state << 8 | byte] = out = to << 10 | (delta + 512)
        return out

    def run(self, data: bytes) -> int:
        """The number of tokens of a pre-token: the sum of the changes along its path."""
        if len(self.states) > MOST_STATES:
            self._restart()
        state, count, steps = 0, 0, self.steps.get
        for b in data:
            t = steps(state << 8 | b) or self._step(state, b)
            state = t >> 10
            count += (t & 1023) - 512
        return count

    def plain(self, text: str) -> int:
        return sum(map(self.words.__getitem__, self.find(text)))

    def between(self, text: str) -> int:
        """Tokens of a stretch of text; special strings in it are one token each."""
        if self.cut is None or not any(s in text for s in self.special):
            return self.plain(text)
        parts = self.cut.split(text)
        return sum(map(self.plain, parts)) + len(parts) - 1

    def _cuts(self, text: str, low: int = 0) -> Iterator[int]:
        """The places from low on where the pre-tokeniser cuts whatever is before."""
        return (m.start() for m in self.sync.finditer(text, low) if text[m.start() - 1 : m.start() + 1] not in self.whole)

    def chunk_map(self, text: str) -> tuple[str, int, str] | str:
        """A chunk's map: (before the first cut, tokens between, from the last cut on), or the chunk itself if it has no cut."""
        first = next(self._cuts(text), None)
        if first is None:
            return text
        last, back = first, 256
        while True:  # the last cut, sought from the end in growing windows
            low = max(first, len(text) - back)
            found = max(self._cuts(text, low), default=None)
            if found is not None or low == first:
                last = first if found is None else found
                break
            back *= 4
        return text[:first], self.between(text[first:last]), text[last:]

    def compose(self, x, y):
        """The map of two adjoining chunks."""
        if isinstance(x, str) and isinstance(y, str):
            return self._joined(x, y)
        if isinstance(x, str):
            seam = self._joined(x, y[0])
            return (seam, y[1], y[2]) if isinstance(seam, str) else (seam[0], seam[1] + self.between(seam[2]) + y[1], y[2])
        if isinstance(y, str):
            seam = self._joined(x[2], y)
            return (x[0], x[1], seam) if isinstance(seam, str) else (x[0], x[1] + self.between(seam[0]) + seam[1], seam[2])
        return x[0], x[1] + self.between(x[2] + y[0]) + y[1], y[2]

    def _joined(self, a: str, b: str):
        """a + b, cut if the seam between them is one."""
        if a and b and next(self._cuts(a[-1] + b[0], 1), None) == 1:
            return a, 0, b
        return a + b

    def scan(self, maps: list):
        """The map of neighbouring chunks, composed as a balanced tree."""
        while len(maps) > 1:
            maps = [self.compose(*maps[i : i + 2]) if i + 1 < len(maps) else maps[i] for i in range(0, len(maps), 2)]
        return maps[0]

    def finished(self, whole) -> int:
        """The tokens of a text from its map."""
        return self.between(whole) if isinstance(whole, str) else self.between(whole[0]) + whole[1] + self.between(whole[2])

    def count(self, text: str | None) -> int:
        """The tokens of a text, in one go."""
        return self.between(text) if text else 0

    def count_by_chunks(self, text: str, size: int) -> int:
        """As count, by the maps of chunks."""
        return self.finished(self.scan([self.chunk_map(text[i : i + size]) for i in range(0, len(text), size)])) if text else 0


@lru_cache(maxsize=2)
def transducer(path: str) -> BpeTransducer:
    """One compiled transducer per Python worker; the file is found on the executor by its path."""
    with open(path, encoding="utf-8") as f:
        return BpeTransducer(json.load(f))


MAP = "digest string, place int, before string, tokens long, after string"


def _as_row(found) -> tuple:
    """A map as (before, tokens, after); a chunk without a cut has no tokens and no after."""
    return (found, None, None) if isinstance(found, str) else found


def _mapped(path: str):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        t = transducer(path)
        for batch in batches:
            rows = [(d, k, *_as_row(t.chunk_map(x))) for d, k, x in zip(batch["digest"], batch["place"], batch["chunk"], strict=True)]
            yield _frame(rows)

    return run


def _frame(rows: list[tuple]) -> pd.DataFrame:
    return pd.DataFrame(rows, columns=["digest", "place", "before", "tokens", "after"]).astype({"tokens": "Int64"})


def _composed(path: str):
    def run(rows: pd.DataFrame) -> pd.DataFrame:
        """Neighbouring maps of one text as one."""
        t, rows = transducer(path), rows.sort_values("place")
        maps = [b if pd.isna(n) else (b, int(n), a) for b, n, a in zip(rows["before"], rows["tokens"], rows["after"], strict=True)]
        return _frame([(rows["digest"].iloc[0], int(rows["place"].iloc[0]) // FAN, *_as_row(t.scan(maps)))])

    return run


def _long_counts(rows: DataFrame, path: str, chunk: int) -> DataFrame:
    """(digest, n) of the texts of more than chunk characters: their chunks' maps, composed in rounds of FAN neighbours."""
    long = rows.filter(F.length("text") > chunk).select(F.md5("text").alias("digest"), "text")
    places = F.sequence(F.lit(0), F.floor((F.length("text") - 1) / chunk).cast("int"))
    cut = long.select("digest", "text", F.explode(places).alias("place")).select("digest", "place", F.substring(F.col("text"), (F.col("place") * chunk + 1).cast("int"), F.lit(chunk)).alias("chunk"))
    # copies of a text have the same chunks
    maps = stored(cut.mapInPandas(_mapped(path), MAP).dropDuplicates(["digest", "place"]), "chunk-maps")
    while (maps.agg(F.max("place")).first()[0] or 0) > 0:
        maps = stored(maps.groupBy("digest", F.expr(f"place div {FAN}").alias("group")).applyInPandas(_composed(path), MAP), "chunk-maps")

    @F.pandas_udf(LongType())
    def finished(before: pd.Series, tokens: pd.Series, after: pd.Series) -> pd.Series:
        t = transducer(path)
        return pd.Series([t.finished(b if pd.isna(n) else (b, int(n), a)) for b, n, a in zip(before, tokens, after, strict=True)], dtype="int64")

    return stored(maps.select("digest", finished("before", "tokens", "after").alias("n")), "long-counts")


def token_counts(docs: DataFrame, tokenizer_path: str, key: str = "doc_id", text: str = "text", limit: int = LIMIT, chunk: int = CHUNK_CHARS) -> DataFrame:
    """key, n_bytes, n_tokens, over_limit for each row of docs.

    Null and empty texts have 0 bytes and 0 tokens; repeated rows and null keys are kept as they come; extra columns
    are ignored. Texts of up to ``chunk`` characters are counted where they lie; longer ones by chunk. A
    stretch of one kind of character (a run of letters, say) that is longer than a chunk is carried whole.
    """
    rows = pick(docs, key, text).toDF("key", "text")

    @F.pandas_udf(LongType())
    def n_tokens(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        count = transducer(tokenizer_path).count
        for batch in texts:
            yield pd.Series([count(t) for t in batch], dtype="int64")

    is_long = F.coalesce(F.length("text") > chunk, F.lit(False))
    long = broadcast_if_small(_long_counts(rows, tokenizer_path, chunk), 100)
    counted = rows.select(
        "key",
        F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"),
        n_tokens(F.when(~is_long, F.col("text"))).alias("short"),
        F.when(is_long, F.md5("text")).alias("digest"),
    )
    out = counted.join(long, "digest", "left").select(F.col("key").alias(key), "n_bytes", F.coalesce("n", "short").alias("n_tokens"))
    return out.withColumn("over_limit", F.col("n_tokens") > limit)


def op5_transducer_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return token_counts(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
