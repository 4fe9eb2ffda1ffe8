"""Byte-level BPE encoding and decoding with a given public vocabulary.

Encoding of one pre-token: its symbols form a doubly linked list, every adjacent pair that
has a merge waits in a priority queue under (rank, position), and a popped entry whose
symbols have changed meanwhile is stale and skipped.  Pre-tokens repeat, so their encodings
are kept in a bounded table.  Decoding concatenates the vocabulary's byte strings.

Null and empty texts have no tokens; repeated rows and ids give rows of their own; other columns,
whatever their names, are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import struct
from itertools import islice

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nearcohort.llm.textblocks import BLOCK_BYTES, hold
from nearcohort.plans.runtime import ship

#: Pre-tokens whose encodings a task keeps; the table is emptied when it is full.
CACHE_WORDS = 200_000
#: Pre-tokens longer than this are encoded each time.
CACHE_CHARS = 64
#: Fixed value: the pattern that byte-level vocabularies split text by.
SPLIT = (r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+")


def byte_letters() -> list[str]:
    """The printable character that stands for each byte in the vocabulary file."""
    shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
    hidden = iter(range(256, 512))
    return [chr(b) if b in shown else chr(next(hidden)) for b in range(256)]


class Codec:
    """A vocabulary with its merges; encodes and decodes single texts."""

    def __init__(self, spec: dict):
        letters = byte_letters()
        back = {c: b for b, c in enumerate(letters)}
        vocab, added = spec["model"]["vocab"], {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.strings = [b""] * (1 + max([*vocab.values(), *added.values()]))
        for token, i in vocab.items():
            self.strings[i] = bytes(back[c] for c in token) if all(c in back for c in token) else token.encode()
        for token, i in added.items():
            self.strings[i] = token.encode()
        self.byte_ids = [vocab[c] for c in letters]
        pairs = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        #: rank of a pair of ids (in one integer), and the id that the merge of that rank makes
        self.ranks = {vocab[a] << 32 | vocab[b]: rank for rank, (a, b) in enumerate(pairs)}
        self.made = [vocab[a + b] for a, b in pairs]
        self.split = regex.compile(SPLIT)
        self.added = regex.compile("(" + "|".join(map(regex.escape, sorted(added, key=len, reverse=True))) + ")") if added else None
        self.added_ids = added
        self.known: dict[str, bytes] = {}

    def merge(self, raw: bytes) -> list[int]:
        """Ids of one pre-token."""
        sym = [self.byte_ids[b] for b in raw]
        n, rank_of, made = len(sym), self.ranks.get, self.made
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        # an entry is (rank, place of the left symbol) in one integer
        queue = [r << 32 | i for i in range(n - 1) if (r := rank_of(sym[i] << 32 | sym[i + 1])) is not None]
        heapq.heapify(queue)
        while queue:
            entry = heapq.heappop(queue)
            i, rank = entry & 0xFFFFFFFF, entry >> 32
            j = after[i]
            if j >= n or rank_of(sym[i] << 32 | sym[j]) != rank:
                continue  # stale: one of its symbols has been merged meanwhile
            new, k, p = made[rank], after[j], before[i]
            sym[i], sym[j], after[i] = new, -1, k
            if k < n:
                before[k] = i
                if (r := rank_of(new << 32 | sym[k])) is not None:
                    heapq.heappush(queue, r << 32 | i)
            if p >= 0 and (r := rank_of(sym[p] << 32 | new)) is not None:
                heapq.heappush(queue, r << 32 | p)
        return [s for s in sym if s >= 0]

    def _words(self, words: list[str]) -> bytes:
        """Ids of pre-tokens one after the other; those not met before are merged once."""
        known = self.known
        try:
            return b"".join([known[w] for w in words])
        except KeyError:
            pass
        new = {w: self._packed(w) for w in set(words) if w not in known}
        keep = new if len(new) < CACHE_WORDS else dict(islice(new.items(), CACHE_WORDS))
        keep = {w: x for w, x in keep.items() if len(w) <= CACHE_CHARS}
        if len(known) + len(keep) <= CACHE_WORDS and len(keep) == len(new):
            known.update(keep)
            return b"".join([known[w] for w in words])
        out = b"".join([known[w] if w in known else new[w] for w in words])
        if len(known) + len(keep) > CACHE_WORDS:
            known.clear()
        known.update(keep)
        return out

    def _packed(self, word: str) -> bytes:
        ids = self.merge(word.encode("utf-8", "replace"))
        return struct.pack(f"<{len(ids)}I", *ids)

    def encode(self, text: str | None) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        if not text:
            return b""
        if self.added is None or self.added.search(text) is None:
            return self._words(self.split.findall(text))
        out = []
        for part in self.added.split(text):
            if part in self.added_ids:
                out.append(np.uint32(self.added_ids[part]).tobytes())
            elif part:
                out.append(self._words(self.split.findall(part)))
        return b"".join(out)

    def decode(self, ids: bytes) -> bytes:
        strings = self.strings
        return b"".join([strings[i] for i in np.frombuffer(ids, "<u4").tolist()])


def codec(spec: str) -> Codec:
    """The codec of a vocabulary given as JSON text, kept until another operator needs the worker."""
    return hold(("codec", spec), lambda: Codec(json.loads(spec)))


def _encode(batches, spec):
    tool = codec(spec.value)
    for b in batches:
        ids, texts = b.column("doc_id"), b.column("text")
        done, start, size = [], 0, 0
        for r in range(len(texts)):
            done.append(tool.encode(texts[r].as_py()))
            size += len(done[-1])
            if size > 16 * BLOCK_BYTES or r == len(texts) - 1:
                yield pa.RecordBatch.from_arrays(
                    [ids.slice(start, len(done)), pa.array([len(x) // 4 for x in done], pa.int64()),
                     pa.array(done, pa.binary())], ["doc_id", "n_tokens", "ids"])
                done, start, size = [], r + 1, 0


def _decode(batches, spec, rest):
    tool = codec(spec.value)
    for b in batches:
        ids = b.column("ids")
        text = [None if not x.is_valid else tool.decode(x.as_py()).decode("utf-8", "replace") for x in ids]
        yield pa.RecordBatch.from_arrays([*(b.column(c) for c in rest), pa.array(text, pa.string())], [*rest, "text"])


def encode(docs: DataFrame, vocabulary: str) -> DataFrame:
    """``doc_id, n_tokens, ids`` of every whole text; ``vocabulary`` is a tokenizer file.

    ``ids`` packs the token ids as little-endian unsigned 32-bit integers.  Null and empty
    texts have no tokens.  Strings of added tokens become these tokens.
    """
    spark = docs.sparkSession
    ship(spark)
    with open(vocabulary, encoding="utf-8") as f:
        spec = spark.sparkContext.broadcast(f.read())
    return (docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
            .mapInArrow(lambda it: _encode(it, spec), "doc_id long, n_tokens long, ids binary"))


def decode(encoded: DataFrame, vocabulary: str) -> DataFrame:
    """Adds ``text`` in place of ``ids``; bytes that are no UTF-8 become U+FFFD."""
    spark = encoded.sparkSession
    ship(spark)
    with open(vocabulary, encoding="utf-8") as f:
        spec = spark.sparkContext.broadcast(f.read())
    rest = [c for c in encoded.columns if c not in ("ids", "text")]
    kinds = ", ".join(f"`{c}` {t}" for c, t in encoded.select(*rest).dtypes)
    return (encoded.select(*rest, "ids")
            .mapInArrow(lambda it: _decode(it, spec, rest), f"{kinds}, text string" if kinds else "text string"))


def _both_ways(batches, spec):
    tool = codec(spec.value)
    for b in batches:
        n, ids_sha, text_sha = [], [], []
        for t in b.column("text"):
            ids = tool.encode(t.as_py())
            text = tool.decode(ids).decode("utf-8", "replace")
            n.append(len(ids) // 4)
            ids_sha.append(hashlib.sha256(ids).hexdigest())
            text_sha.append(hashlib.sha256(text.encode()).hexdigest())
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())],
                                         ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])


def round_trip(docs: DataFrame, vocabulary: str) -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256``: both directions over whole texts.

    One worker does both, so that ids don't travel and a task holds one codec.
    """
    spark = docs.sparkSession
    ship(spark)
    with open(vocabulary, encoding="utf-8") as f:
        spec = spark.sparkContext.broadcast(f.read())
    return (docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
            .mapInArrow(lambda it: _both_ways(it, spec), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"))
