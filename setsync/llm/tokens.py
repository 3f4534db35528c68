"""Token ids and counts with public vocabularies, through two tiers of look-up and no shuffle.

Counts: the driver encodes the pre-tokens of a bounded sample once and broadcasts the lengths of the
frequent ones; a worker looks every pre-token up there, then in its own cache, and encodes what is
left. The sample speeds the look-up alone: every count is the library's. Ids: the same two steps on
white-space chunks. Texts that hold the strings of added tokens or control separators, where chunks
are not independent, go whole to the library.

Defined cases: null and empty texts have no tokens; ties and repeated rows are counted like any other.
"""

from __future__ import annotations

import json
import unicodedata
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import public_tokenizers
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from tokenizers import Tokenizer

from setsync.llm.shared import bounded_batches, table

#: Rows of the sample and entries of the broadcast table, at most.
SAMPLE_ROWS = 500
FREQUENT = 32_768
#: Entries of a worker's own cache.
CACHE = 200_000
#: Characters of a cached key, at most; longer ones are rare and made anew.
KEY = 64
LIMIT = 512
#: Bytes of a piece that is merged in numpy, at most; a rank above all ranks; bytes of a block of texts.
LONGEST = 64
NEVER = 2**31 - 1
BLOCK_BYTES = 4 << 20

PRE_TOKEN = regex.compile(
    r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"
)
#: A line break parts the chunks of a block.
CHUNK_PIECE = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\p{White_Space}\p{L}\p{N}]+|\n")
MARK = b"\xff\xff\xff\xff"  # no part of any id, all of which stay under 2^24
SEPARATORS = regex.compile("[\x1c-\x1f]")
#: What texts must hold to be taken whole, as Arrow searches for it.
ODD = r"<\||[\x1c-\x1f]"


@lru_cache(maxsize=4)
def load(path: str) -> tuple[Tokenizer, "regex.Pattern | None"]:
    tokenizer = Tokenizer.from_file(path)
    added = [t.content for t in tokenizer.get_added_tokens_decoder().values()]
    return tokenizer, regex.compile("|".join(map(regex.escape, added))) if added else None


@lru_cache(maxsize=1)
def byte_letters() -> list[str]:
    """The printable letter that stands for each byte: itself, or the next free one from 256 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b if b in plain else next(spare)) for b in range(256)]


def as_letters(piece: str) -> str:
    letters = byte_letters()
    return "".join([letters[b] for b in piece.encode()])


class Lengths:
    """Numbers of tokens of byte-level texts; ``frequent`` is the broadcast tier."""

    def __init__(self, path: str, frequent: dict[str, int]):
        self.tokenizer, self.added = load(path)
        self.frequent, self.own = frequent, {}

    def miss(self, piece: str) -> int:
        n = self.own.get(piece)
        if n is None:
            n = len(self.tokenizer.model.tokenize(as_letters(piece)))
            if len(self.own) >= CACHE:
                self.own.clear()
            if len(piece) <= KEY:
                self.own[piece] = n
        return n

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if self.added is not None and self.added.search(text):
            return len(self.tokenizer.encode(text, add_special_tokens=False).ids)
        known, total = self.frequent.get, 0
        pieces = PRE_TOKEN.findall(text)
        found = list(map(known, pieces))
        if None in found:
            miss = self.miss
            return sum([n if n is not None else miss(p) for n, p in zip(found, pieces)])
        return sum(found)


def frequent_lengths(texts: list[str | None], path: str, entries: int = FREQUENT) -> dict[str, int]:
    seen: Counter = Counter()
    for text in texts:
        seen.update(PRE_TOKEN.findall(text or ""))
    model = load(path)[0].model
    return {p: len(model.tokenize(as_letters(p))) for p, _ in seen.most_common(entries)}


def token_counts(docs: DataFrame, path: str, text_col: str = "text", sample_rows: int = SAMPLE_ROWS):
    """A column with each text's number of tokens. Looks at ``sample_rows`` rows of ``docs`` on the driver."""
    bounded_batches(docs.sparkSession)
    sample = [r[0] for r in docs.select(text_col).limit(sample_rows).collect()]
    shared = docs.sparkSession.sparkContext.broadcast(frequent_lengths(sample, path))

    @F.pandas_udf(T.LongType())
    def count(parts: "pd.Series") -> "pd.Series":
        lengths = worker_lengths(path, shared)
        return pd.Series([lengths.count(t) for t in parts], dtype="int64")

    return count(F.col(text_col))


WORKER: dict = {}


def worker_lengths(path: str, shared) -> Lengths:
    key = (path, id(shared.value))
    if WORKER.get("key") != key:
        WORKER.update(key=key, lengths=Lengths(path, shared.value))
    return WORKER["lengths"]


class Merger:
    """Byte-pair merging of many pieces at once: a round merges each piece's pair of lowest rank, the leftmost of equals.

    Pairs are looked up in an open-addressed table of (left id, right id); pieces above ``LONGEST`` bytes
    are left to the library.
    """

    #: Slots (a power of two; with 50,000 merges the table stays in a core's cache) and bits of an id or rank.
    SLOT_BITS, FACTOR, WIDTH = 17, 0x9E3779B97F4A7C15, 21
    #: Pieces merged together: few enough for their arrays to stay in the cache too.
    TOGETHER = 1 << 15

    def __init__(self, path: str):
        self.model = load(path)[0].model
        with open(path, encoding="utf-8") as f:
            plan = json.load(f)["model"]
        vocab, suffix = plan["vocab"], plan.get("end_of_word_suffix") or ""
        self.first = np.array([vocab[x] for x in byte_letters()], np.int64)
        self.final = np.array([vocab[x + suffix] for x in byte_letters()], np.int64)
        pairs = [m.split(" ") if isinstance(m, str) else m for m in plan["merges"]]
        keys = np.array([vocab[x] << self.WIDTH | vocab[y] for x, y in pairs], np.int64)
        self.made = np.array([vocab[x + y] if not suffix else vocab[x.removesuffix(suffix) + y] for x, y in pairs], np.int64)
        self.bits = max(self.SLOT_BITS, (2 * len(pairs)).bit_length())
        slots = [-1] * (1 << self.bits)
        for rank, (key, at) in enumerate(zip(keys.tolist(), self.spots(keys).tolist())):
            while slots[at] != -1:
                at = (at + 1) % len(slots)
            slots[at] = key << self.WIDTH | rank
        self.slots = np.array(slots, np.int64)

    def spots(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.view(np.uint64) * np.uint64(self.FACTOR)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of each pair; ``NEVER`` for those that don't merge."""
        keys = left << self.WIDTH | right
        at = self.spots(keys)
        seen = self.slots[at]
        hit = seen >> self.WIDTH == keys
        out = np.where(hit, seen & (1 << self.WIDTH) - 1, NEVER).astype(np.int32)
        asked = np.flatnonzero(~hit & (seen != -1))
        at = at[asked]
        while len(asked):
            at = (at + 1) % len(self.slots)
            seen = self.slots[at]
            hit = seen >> self.WIDTH == keys[asked]
            out[asked[hit]] = seen[hit] & (1 << self.WIDTH) - 1
            on = ~hit & (seen != -1)
            asked, at = asked[on], at[on]
        return out

    def ids(self, pieces: list[str]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each piece (none is empty)."""
        out: list[bytes] = []
        for at in range(0, len(pieces), self.TOGETHER):
            out += self.some_ids(pieces[at : at + self.TOGETHER])
        return out

    def some_ids(self, pieces: list[str]) -> list[bytes]:
        raw = [p.encode() for p in pieces]
        out: list[bytes] = [b""] * len(raw)
        short = [k for k, x in enumerate(raw) if len(x) <= LONGEST]
        for k, x in enumerate(raw):
            if len(x) > LONGEST:
                out[k] = np.array([t.id for t in self.model.tokenize(as_letters(pieces[k]))], "<u4").tobytes()
        if not short:
            return out
        sizes = np.array([len(raw[k]) for k in short])
        letters = np.frombuffer(b"".join([raw[k] for k in short]), np.uint8)
        owner, ends = np.repeat(np.arange(len(short)), sizes), np.cumsum(sizes) - 1
        symbols = self.first[letters]
        symbols[ends] = self.final[letters[ends]]
        # ``rank[i]`` is that of symbols i and i + 1; a piece's last symbol has none.
        rank = np.append(self.rank(symbols[:-1], symbols[1:]), np.int32(NEVER))
        rank[ends] = NEVER
        done_symbols, done_owner = [], []
        while True:
            starts = np.flatnonzero(np.diff(owner, prepend=-1))
            least = np.minimum.reduceat(rank, starts)
            counts = np.diff(np.append(starts, len(owner)))
            going = least < NEVER
            if not going.all():
                over = np.repeat(~going, counts)
                done_symbols.append(symbols[over])
                done_owner.append(owner[over])
                symbols, owner, rank, least, counts = symbols[~over], owner[~over], rank[~over], least[going], counts[going]
                if not len(symbols):
                    break
            spread = np.repeat(np.arange(len(counts)), counts)
            lowest = np.flatnonzero(rank == least[spread])
            at = lowest[np.diff(spread[lowest], prepend=-1) > 0]
            symbols[at] = self.made[least]
            keep = np.ones(len(symbols), bool)
            keep[at + 1] = False
            at = at - np.arange(len(at))
            symbols, owner, rank = symbols[keep], owner[keep], rank[keep]
            for spot in (at, at - 1):
                spot = spot[spot >= 0]
                pair = spot[spot + 1 < len(owner)]
                rank[spot] = NEVER
                pair = pair[owner[pair] == owner[pair + 1]]
                rank[pair] = self.rank(symbols[pair], symbols[pair + 1])
        owner, symbols = np.concatenate(done_owner), np.concatenate(done_symbols)
        order = np.argsort(owner, kind="stable")
        flat = symbols[order].astype("<u4").tobytes()
        edges = np.append(0, np.cumsum(np.bincount(owner, minlength=len(short)))) * 4
        for k, a, b in zip(short, edges[:-1].tolist(), edges[1:].tolist()):
            out[k] = flat[a:b]
        return out


@lru_cache(maxsize=2)
def merger(path: str) -> Merger:
    return Merger(path)


class Recent:
    """A bounded cache of two generations: what is used stays, what was not used in a generation goes."""

    def __init__(self, entries: int = 2 * CACHE):
        self.half, self.new, self.old = entries // 2, {}, {}

    def take(self, keys: set[str]) -> set[str]:
        """Brings known keys into the new generation; the unknown ones are returned."""
        if len(self.new) >= self.half:
            self.new, self.old = {}, self.new
        missing = keys.difference(self.new)
        back = missing.intersection(self.old)
        self.new.update((k, self.old[k]) for k in back)
        return missing - back


class ChunkIds:
    """Ids of texts whose vocabulary lower-cases, composes and drops white space, by distinct chunks of a block of texts."""

    def __init__(self, path: str, entries: int = 2 * CACHE, block_bytes: int = BLOCK_BYTES):
        self.tokenizer, self.added = load(path)
        self.merger, self.chunks, self.pieces, self.block_bytes = merger(path), Recent(entries), Recent(entries), block_bytes

    def learn(self, chunks: list[str]) -> None:
        text = unicodedata.normalize("NFC", "\n".join(chunks))
        text = "".join([c.lower() for c in text]) if "Σ" in text else text.lower()
        flat = CHUNK_PIECE.findall(text)
        new = list(self.pieces.take(set(flat) - {"\n"}))
        known = self.pieces.new
        known.update(zip(new, self.merger.ids(new)))
        known["\n"] = MARK
        self.chunks.new.update(zip(chunks, b"".join(map(known.__getitem__, flat)).split(MARK)))
        for piece in [p for p in new if len(p) > KEY]:
            del known[piece]

    def whole(self, text: str) -> bool:
        return bool((self.added is not None and "<|" in text and self.added.search(text)) or SEPARATORS.search(text))

    def known_ids(self, words: list[str]) -> list[bytes]:
        self.learn(list(self.chunks.take(set(words) - {""})))
        known = self.chunks.new
        out = [known[w] if w else b"" for w in words]
        for word in {w for w in words if len(w) > KEY}:
            del known[word]
        return out

    def encode_block(self, column: pa.Array) -> list[bytes]:
        """Words stay in Arrow: its dictionary gives the distinct ones, and an index into their ids the rest."""
        odd = pc.fill_null(pc.match_substring_regex(column, ODD), False)
        lists = pc.utf8_split_whitespace(pc.if_else(odd, "", pc.fill_null(column, "")).cast(pa.large_string()))
        coded = lists.flatten().dictionary_encode()
        index, parts = coded.indices.to_numpy(), self.known_ids(coded.dictionary.to_pylist())
        sizes = np.fromiter(map(len, parts), np.int64, len(parts)) // 4
        starts = (np.cumsum(sizes) - sizes)[index]
        flat, counts = np.frombuffer(b"".join(parts), "<u4"), sizes[index]
        ends = np.cumsum(counts)
        ids = flat[np.arange(len(counts) and ends[-1]) + np.repeat(starts - ends + counts, counts)]
        offsets = lists.offsets.to_numpy()
        edges = np.append(0, ends)[offsets - offsets[0]].tolist()
        out = [ids[a:b].tobytes() for a, b in zip(edges, edges[1:])]
        for k in np.flatnonzero(odd.to_numpy(zero_copy_only=False)).tolist():
            text = column[k].as_py()
            if self.whole(text):
                out[k] = np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
            else:
                out[k] = b"".join(self.known_ids(text.split()))
        return out

    def encode_column(self, column: pa.Array) -> Iterator[bytes]:
        """Little-endian unsigned 32-bit ids of each text, in blocks of about ``block_bytes``."""
        sizes = np.cumsum(pc.fill_null(pc.binary_length(column), 0).to_numpy())
        at = 0
        while at < len(column):
            upto = max(at + 1, int(np.searchsorted(sizes, (sizes[at - 1] if at else 0) + self.block_bytes, "right")))
            yield from self.encode_block(column.slice(at, upto - at))
            at = upto

    def encode(self, text: str | None) -> bytes:
        return self.encode_block(pa.array([text], pa.string()))[0]


@lru_cache(maxsize=1)
def chunk_ids(path: str, entries: int = 2 * CACHE, block_bytes: int = BLOCK_BYTES) -> ChunkIds:
    return ChunkIds(path, entries, block_bytes)


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    counted = docs.select(
        "doc_id",
        F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"),
        token_counts(docs, public_tokenizers.path("byte_bpe_50k.json")).alias("n_tokens"),
    )
    return counted.withColumn("over_limit", F.col("n_tokens") > LIMIT)
