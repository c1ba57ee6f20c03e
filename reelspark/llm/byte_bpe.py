"""Byte-level BPE with the tokenizers library, from a file of ranks.

The ranks name tokens as bytes; the library wants characters, so every byte is mapped to a printable
character and back. Each match of the pattern (a piece) is encoded once per worker and remembered
(up to ``REMEMBER`` pieces of at most ``LONGEST`` characters; then the memory starts anew), which bounds memory for texts of any length.
Decoding joins the tokens' bytes through the reversed byte table; a character whose bytes are split
over tokens is whole again once they are joined, and ``StreamDecoder`` holds back its first bytes.

Defined results: a null or empty text has no tokens and the hashes of empty strings.
"""

from __future__ import annotations

import codecs
import functools
import hashlib
import itertools
from collections.abc import Iterable, Iterator

import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reelspark.llm.common import per_document

RANKS = "byte_bpe_multi_50k.tiktoken"
REMEMBER, LONGEST = 400_000, 128


@functools.cache
def byte_table() -> dict[int, str]:
    """Printable Latin-1 bytes stand for themselves, the rest for characters from 256 on, in order."""
    plain = [b for b in range(256) if chr(b).isprintable() and not chr(b).isspace()]
    free = itertools.count(256)
    return {b: chr(b) if b in plain else chr(next(free)) for b in range(256)}


def as_chars(data: bytes) -> str:
    table = byte_table()
    return "".join([table[b] for b in data])


class ByteBpe:
    def __init__(self, path: str, pattern: str):
        import base64

        from tokenizers import Tokenizer, models, pre_tokenizers

        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        # a pair may be merged if its join is a token; pairs of one token follow each other in rank
        merges = [(as_chars(t[:k]), as_chars(t[k:])) for t, _ in sorted(ranks.items(), key=lambda x: x[1]) for k in range(1, len(t)) if t[:k] in ranks and t[k:] in ranks]
        self.library = Tokenizer(models.BPE(vocab={as_chars(t): r for t, r in ranks.items()}, merges=merges, ignore_merges=True))
        self.library.pre_tokenizer = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        self.bytes = {r: t for t, r in ranks.items()}
        self.pattern = regex.compile(pattern)
        self.known: dict[str, tuple[int, ...]] = {}

    def learn(self, pieces: Iterable[str]) -> None:
        """Encodes the pieces that are not yet known; long ones are not remembered."""
        pieces = [p for p in dict.fromkeys(pieces) if len(p) <= LONGEST]
        new = [p for p in pieces if p not in self.known]
        if len(self.known) + len(new) > REMEMBER:
            self.known.clear()
            new = pieces
        for at in range(0, len(new), 4096):
            part = new[at : at + 4096]
            for p, e in zip(part, self.library.encode_batch_fast(part, add_special_tokens=False), strict=True):
                self.known[p] = tuple(e.ids)

    def ids_of(self, pieces: list[str]) -> list[tuple[int, ...]]:
        """The ids of each piece."""
        try:
            return list(map(self.known.__getitem__, pieces))
        except KeyError:
            self.learn(pieces)
            return [self.known[p] if len(p) <= LONGEST else tuple(self.library.encode(p, add_special_tokens=False).ids) for p in pieces]

    def pieces(self, text: str, most: int = 100_000) -> Iterator[list[str]]:
        """The pattern's matches, in lists of bounded length."""
        if len(text) < most:
            yield self.pattern.findall(text)
            return
        found = (m.group() for m in self.pattern.finditer(text))
        while part := list(itertools.islice(found, most)):
            yield part

    def encode(self, text: str) -> list[int]:
        out: list[int] = []
        for part in self.pieces(text):
            out += itertools.chain.from_iterable(self.ids_of(part))
        return out

    def offsets(self, ids: list[int]) -> list[tuple[int, int]]:
        """Byte span of each token in the text's UTF-8 form."""
        ends = list(itertools.accumulate(len(self.bytes[i]) for i in ids))
        return list(zip([0, *ends], ends, strict=False))

    def decode_bytes(self, ids: Iterable[int]) -> bytes:
        return b"".join(map(self.bytes.__getitem__, ids))


class StreamDecoder:
    """Decodes ids in parts: characters come out as soon as their last byte is there."""

    def __init__(self, bpe: ByteBpe):
        self.bpe, self.held = bpe, codecs.getincrementaldecoder("utf-8")("replace")

    def feed(self, ids: Iterable[int], final: bool = False) -> str:
        return self.held.decode(self.bpe.decode_bytes(ids), final)


@functools.cache
def shared(path: str | None = None, pattern: str | None = None) -> ByteBpe:
    """One encoder per worker process."""
    import os

    import public_tokenizers

    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    return ByteBpe(path or public_tokenizers.path(RANKS), pattern or public_tokenizers.PATTERN)


@functools.cache
def numerals(n: int) -> list[str]:
    return [str(i) for i in range(n)]


def encode(docs: DataFrame, path: str | None = None, pattern: str | None = None, text: str = "text") -> DataFrame:
    """doc_id, ids and the byte offset where each token starts."""

    def run(cols: list[list]) -> list[list]:
        bpe = shared(path, pattern)
        ids = [bpe.encode(t or "") for t in cols[1]]
        return [cols[0], ids, [[a for a, _ in bpe.offsets(i)] for i in ids]]

    return per_document(docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col(text)), ["doc_id", text], "doc_id bigint, ids array<int>, starts array<int>", run)


def decode(encoded: DataFrame, path: str | None = None, pattern: str | None = None) -> DataFrame:
    """doc_id and text from (doc_id, ids); bytes that form no character become the replacement character."""

    def run(cols: list[list]) -> list[list]:
        bpe = shared(path, pattern)
        return [cols[0], [bpe.decode_bytes(i or ()).decode("utf-8", "replace") for i in cols[1]]]

    return per_document(encoded.select(F.col("doc_id").cast("bigint").alias("doc_id"), "ids"), ["doc_id", "ids"], "doc_id bigint, text string", run)


def digest(docs: DataFrame, path: str | None = None, pattern: str | None = None, also: str = "") -> DataFrame:
    """The columns that op6 returns (and the string column ``also``), without holding a corpus of ids."""

    def run(cols: list[list]) -> list[list]:
        bpe = shared(path, pattern)
        names = numerals(max(bpe.bytes) + 1)
        counts, a, b = [], [], []
        for t in cols[1]:
            ids = bpe.encode(t or "")
            counts.append(len(ids))
            a.append(hashlib.sha256(",".join(map(names.__getitem__, ids)).encode()).hexdigest())
            b.append(hashlib.sha256(bpe.decode_bytes(ids)).hexdigest())
        return [cols[0], *cols[2:], counts, a, b]

    extra = [also] if also else []
    schema = "doc_id bigint, " + "".join(f"{c} string, " for c in extra) + "n_tokens bigint, ids_sha256 string, decoded_sha256 string"
    return per_document(docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text", *extra), ["doc_id", "text", *extra], schema, run)
