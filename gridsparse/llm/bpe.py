"""Byte-level BPE by prefix dynamic programming, and its op2 query.

For every byte prefix of a piece exactly one token can end its encoding.  The
encoder stores that token per prefix: a token ``t`` that ends at ``i`` is the
one iff its start is 0 or it may stand after the stored last token of the
prefix before it.  Two tokens may stand side by side iff no merge would ever
have crossed their seam, which the merge trees of the two decide.  The stored
table makes appends exact and edits local: ``Encoded`` keeps a text's pieces,
encodes anew those that an edit reaches, and extends a piece's table where text
is added to it.

Character classes are those of the tokenizer library's own pattern engine, asked
once per process for all code points.

Texts: null and empty give no token; length is unbounded (work is linear in it
times the longest token).  Rows repeat as they are in the input.
"""

from __future__ import annotations

import base64
import functools
import hashlib
import re
import sys
from itertools import accumulate

import ahocorasick
import numpy as np
import pyarrow as pa
import tiktoken
from pyspark.sql import DataFrame, SparkSession

from gridsparse.llm import common

VOCABULARY = "byte_bpe_multi_50k.tiktoken"
CACHE_ENTRIES = 80_000
SEAM_ENTRIES = 250_000
LONGEST_CACHED = 64  # characters of a piece that a cache keeps
#: Characters before an edit up to which a piece's end may depend on it: the pattern looks at most three ahead.
LOOKAHEAD = 3


class Generations(dict):
    """A memo of bounded size: a full generation becomes the old one, hits in it come back."""

    def __init__(self, make, entries: int = CACHE_ENTRIES):
        super().__init__()
        self.make, self.entries, self.old = make, entries, {}

    def __missing__(self, key):
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
        if len(self) >= self.entries:
            self.old = dict(self)
            self.clear()
        self[key] = value
        return value


class PrefixEncoder:
    """Encoder and decoder over tiktoken-style ranks."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks = ranks
        self.token_bytes: list[bytes] = [b""] * (max(ranks.values(), default=-1) + 1)
        for raw, rank in ranks.items():
            self.token_bytes[rank] = raw
        self.longest = max(map(len, ranks), default=1)
        self.packed = [i.to_bytes(4, "little") for i in range(len(self.token_bytes))]
        self._halves: dict[int, tuple[int, int] | None] = {}
        self._seams = Generations(self._seam_holds, SEAM_ENTRIES)
        self._pieces = Generations(self._piece_ids)
        self._wide, self._latin = (re.compile(_classes(pattern, most)) for most in (0x110000, 0x250))
        self._beyond = re.compile("[\u0250-\U0010ffff]")

    # -- merge trees ---------------------------------------------------------
    def halves(self, token: int) -> tuple[int, int] | None:
        """The two tokens whose merge makes ``token``; itself twice for a byte, None if no merge does."""
        known = self._halves.get(token, 0)
        if known != 0:
            return known
        raw = self.token_bytes[token]
        parts = [raw[i : i + 1] for i in range(len(raw))]
        result: tuple[int, int] | None = (token, token) if len(parts) == 1 else None
        while len(parts) > 1:
            rank, at = min(((self.ranks.get(a + b, sys.maxsize), i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False))))
            if rank == sys.maxsize:
                break
            if len(parts) == 2:
                result = (self.ranks[parts[0]], self.ranks[parts[1]])
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        self._halves[token] = result
        return result

    def _seam_holds(self, pair: int) -> bool:
        """Whether no merge crosses the seam while the two tokens form, seen from the last merge back.

        ``pair`` is the left token times 2**32 plus the right one.
        """
        left, right = pair >> 32, pair & 0xFFFFFFFF
        raw, ranks = self.token_bytes, self.ranks
        before = sys.maxsize  # a crossing merge of a rank below this would have come first
        while True:
            if ranks.get(raw[left] + raw[right], sys.maxsize) < before:
                return False
            age_left = left if len(raw[left]) > 1 else -1
            age_right = right if len(raw[right]) > 1 else -1
            if age_left < 0 and age_right < 0:
                return True
            if age_left > age_right:
                before, left = age_left, self.halves(left)[1]
            else:  # merges of equal rank go from left to right, so the crossing one wins a tie here
                before, right = age_right + 1, self.halves(right)[0]

    # -- the prefix table ----------------------------------------------------
    @functools.cached_property
    def finder(self) -> ahocorasick.Automaton:
        """All tokens that some merge (or a byte) makes, to be found by their end, longest first."""
        found = ahocorasick.Automaton()
        for text, token in self.starts.items():
            found.add_word(text, (len(text), token))
        found.make_automaton()
        return found

    def extend(self, raw: bytes, last: list[int], stop: int | None = None) -> list[int]:
        """Fill ``last`` (the last token of each prefix, from ``len(last) + 1`` bytes on) up to ``stop``."""
        done, seams = len(last), self._seams
        stop = len(raw) if stop is None else stop
        begin = max(0, done + 1 - self.longest)
        for end, (size, token) in self.finder.iter(raw[begin:stop].decode("latin-1")):
            if begin + end == done:
                start = done + 1 - size
                if not start or seams[last[start - 1] << 32 | token]:
                    last.append(token)
                    done += 1
        if done < stop:
            raise ValueError("the ranks lack a byte")
        return last

    def search(self, raw: bytes) -> list[int]:
        """The tokens of ``raw``, as a cross-check of the table, by filling only the prefixes that a longest-first search meets.

        A prefix that was left without reaching the end is never entered again:
        its last token is unique, so nothing else could follow it.
        """
        text, stop = raw.decode("latin-1"), len(raw)
        usable, path = self.starts, self.finder.longest_prefix
        seams, sizes = self._seams, self.token_bytes
        out: list[int] = []
        dead: set[int] = set()
        at, length = 0, path(text[: self.longest])
        while at < stop:
            while length:
                token = usable.get(text[at : at + length])
                if token is not None and (not out or seams[out[-1] << 32 | token]) and at + length not in dead:
                    out.append(token)
                    at += length
                    length = path(text[at : at + self.longest])
                    break
                length -= 1
            else:
                dead.add(at)
                length = len(sizes[out.pop()])
                at -= length
                length -= 1
        return out

    @functools.cached_property
    def starts(self) -> dict[str, int]:
        """The tokens that some merge (or a byte) makes, by their bytes as Latin-1."""
        return {raw.decode("latin-1"): token for raw, token in self.ranks.items() if self.halves(token) is not None}

    def tokens_of(self, raw: bytes, last: list[int]) -> list[int]:
        """Walk the table back from the whole length."""
        out, end = [], len(last)
        while end:
            out.append(last[end - 1])
            end -= len(self.token_bytes[out[-1]])
        return out[::-1]

    def edit(self, old: bytes, last: list[int], start: int, stop: int, new: bytes) -> tuple[bytes, list[int], int]:
        """Replace ``old[start:stop]``: the new bytes, their table, and how many prefixes were computed anew.

        After the edit the table is computed until it has repeated the old one
        over a stretch of the longest token, from where the old entries hold.
        """
        raw = old[:start] + new + old[stop:]
        shift, table = start + len(new) - stop, last[:start]
        alike = 0
        while len(table) < len(raw):
            self.extend(raw, table, len(table) + 1)
            at = len(table) - 1 - shift
            alike = alike + 1 if at >= stop and last[at] == table[-1] else 0
            if alike >= self.longest:
                fresh = len(table) - start
                return raw, table + last[len(table) - shift :], fresh
        return raw, table, len(table) - start

    # -- texts ---------------------------------------------------------------
    def _piece_ids(self, piece: str) -> bytes:
        raw = piece.encode()
        whole = self.ranks.get(raw)
        ids = [whole] if whole is not None else self.tokens_of(raw, self.extend(raw, []))
        return b"".join(map(self.packed.__getitem__, ids))

    def pieces(self, text: str) -> list[str]:
        return (self._wide if self._beyond.search(text) else self._latin).findall(text)

    def encode_packed(self, text: str) -> bytes:
        """The ids as little-endian 32-bit integers."""
        known, make = self._pieces, self._piece_ids
        return b"".join([known[piece] if len(piece) <= LONGEST_CACHED else make(piece) for piece in self.pieces(text)])

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.encode_packed(text), "<u4").tolist()

    def decode(self, ids) -> bytes:
        return b"".join(map(self.token_bytes.__getitem__, ids))


class Encoded:
    """A text with its pieces and their ids, which appends and edits keep up to date."""

    def __init__(self, coder: PrefixEncoder, text: str):
        self.coder, self.text = coder, text
        self.pieces = coder.pieces(text)
        self.packed = [coder._piece_ids(p) for p in self.pieces]
        self.tail: tuple[str, list[int]] = ("", [])  # the last piece and its table, if it was appended to

    def ids(self) -> np.ndarray:
        return np.frombuffer(b"".join(self.packed), "<u4")

    def append(self, more: str) -> int:
        """Add ``more`` at the end; gives the number of pieces encoded."""
        return self.edit(len(self.text), len(self.text), more)

    def edit(self, start: int, stop: int, new: str) -> int:
        """Replace characters ``start`` to ``stop`` by ``new``; gives the number of pieces encoded.

        Pieces that end ``LOOKAHEAD`` characters before the edit stay; from there
        pieces are cut anew until a cut behind the edit falls on an old one.
        """
        ends = list(accumulate(map(len, self.pieces)))
        first = int(np.searchsorted(np.array(ends, np.int64), start - LOOKAHEAD, side="right"))
        at = ends[first - 1] if first else 0
        text, shift = self.text[:start] + new + self.text[stop:], len(new) - (stop - start)
        old_cuts = {end: k + 1 for k, end in enumerate(ends)}
        pieces, packed, behind = self.pieces[:first], self.packed[:first], len(self.pieces)
        pattern = self.coder._wide if self.coder._beyond.search(text) else self.coder._latin
        fresh = 0
        for found in pattern.finditer(text, at):
            piece = found[0]
            pieces.append(piece)
            packed.append(self._ids(piece, first + fresh))
            fresh += 1
            if found.end() >= start + len(new) and found.end() - shift >= stop and (k := old_cuts.get(found.end() - shift)) is not None:
                behind = k
                break
        self.pieces, self.packed, self.text = pieces + self.pieces[behind:], packed + self.packed[behind:], text
        return fresh

    def _ids(self, piece: str, number: int) -> bytes:
        """A piece's ids; the table of a piece that only grew at its end is extended."""
        coder, raw = self.coder, piece.encode()
        if raw in coder.ranks:
            return coder.packed[coder.ranks[raw]]
        known, last = self.tail
        table = coder.extend(raw, list(last) if known and piece.startswith(known) else [])
        self.tail = (piece, table)
        return b"".join(map(coder.packed.__getitem__, coder.tokens_of(raw, table)))


def _classes(pattern: str, most: int) -> str:
    """``pattern`` with its classes spelled out for code points under ``most``."""
    white, letters, numbers = (_ranges(kind, most) for kind in (r"\s", r"\p{L}", r"\p{N}"))
    spelled = pattern.replace(r"[^\s\p{L}\p{N}]", f"[^{white}{letters}{numbers}]").replace(r"(?!\S)", f"(?![^{white}])")
    return spelled.replace(r"\s+", f"[{white}]+").replace(r"\p{L}", f"[{letters}]").replace(r"\p{N}", f"[{numbers}]")


@functools.lru_cache(maxsize=4)
def _members(kind: str) -> np.ndarray:
    """Whether each code point is of a class, by the tokenizer library's pattern engine: an encoding that splits by the class gives back its members only."""
    single = tiktoken.Encoding("class", pat_str=kind, mergeable_ranks={bytes([k]): k for k in range(256)}, special_tokens={})
    marks = np.zeros(0x110001, bool)
    for low in range(0, 0x110000, 0x2000):
        some = "".join(chr(c) for c in range(low, low + 0x2000) if not 0xD800 <= c < 0xE000)
        marks[np.frombuffer(bytes(single.encode_ordinary(some)).decode().encode("utf-32-le"), "<u4")] = True
    return marks


def _ranges(kind: str, most: int) -> str:
    """Code points under ``most`` of a class, as ranges of a character class."""
    marks = _members(kind)[: most + 1].copy()
    marks[most] = False
    edges = np.flatnonzero(np.diff(np.concatenate(([False], marks)).astype(np.int8)))
    return "".join(f"\\U{a:08x}-\\U{b - 1:08x}" for a, b in edges.reshape(-1, 2).tolist())


@functools.lru_cache(maxsize=2)
def encoder(vocabulary: str | None = None) -> PrefixEncoder:
    """The encoder of a rank file (a path), once per process."""
    import public_tokenizers

    with open(vocabulary or public_tokenizers.path(VOCABULARY), "rb") as lines:
        ranks = {base64.b64decode(raw): int(rank) for raw, rank in map(bytes.split, lines)}
    return PrefixEncoder(ranks, public_tokenizers.PATTERN)


def encode_documents(docs: DataFrame, vocabulary: str | None = None, keep_ids: bool = True) -> DataFrame:
    """``doc_id, n_tokens, ids (array), ids_sha256, decoded_sha256`` for every row of ``docs``.

    ``decoded_sha256`` hashes the bytes that decoding the ids gives back.  With
    ``keep_ids`` false the ids stay in the worker.
    """

    def kernel(part: pa.RecordBatch) -> pa.RecordBatch:
        bpe = encoder(vocabulary)
        count, packed, ids_sha, back_sha = [], [], [], []
        for text in part.column("text").to_pylist():
            ids = bpe.encode_packed(text or "")
            count.append(len(ids) // 4)
            ids_sha.append(hashlib.sha256(ids).hexdigest())
            numbers = np.frombuffer(ids, "<u4").tolist()
            back_sha.append(hashlib.sha256(bpe.decode(numbers)).hexdigest())
            packed.append(numbers if keep_ids else None)
        columns = [part.column("doc_id"), pa.array(count, pa.int64()), pa.array(packed, pa.list_(pa.int32())), pa.array(ids_sha, pa.string()), pa.array(back_sha, pa.string())]
        names = ["doc_id", "n_tokens", "ids", "ids_sha256", "decoded_sha256"]
        return pa.RecordBatch.from_arrays(columns, names=names)

    return common.map_slices(docs.select("doc_id", "text"), kernel, "doc_id long, n_tokens long, ids array<int>, ids_sha256 string, decoded_sha256 string")


def encode_edited(rows: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """``doc_id, ids, pieces, pieces_encoded`` of texts after an edit: rows have doc_id, text, start, stop and new.

    Characters ``start`` to ``stop`` (within the text; null: its end) are replaced
    by ``new`` (null: nothing), and only the pieces near them are encoded again.
    """

    def kernel(part: pa.RecordBatch) -> pa.RecordBatch:
        ids, pieces, fresh = [], [], []
        for text, start, stop, new in zip(*(part.column(c).to_pylist() for c in ("text", "start", "stop", "new")), strict=True):
            held = Encoded(encoder(vocabulary), text or "")
            size = len(held.text)
            start = size if start is None else min(max(start, 0), size)
            stop = size if stop is None else min(max(stop, start), size)
            fresh.append(held.edit(start, stop, new or ""))
            ids.append(held.ids().tolist())
            pieces.append(len(held.pieces))
        columns = [part.column("doc_id"), pa.array(ids, pa.list_(pa.int32())), pa.array(pieces, pa.int64()), pa.array(fresh, pa.int64())]
        return pa.RecordBatch.from_arrays(columns, names=["doc_id", "ids", "pieces", "pieces_encoded"])

    return common.map_slices(rows.select("doc_id", "text", "start", "stop", "new"), kernel, "doc_id long, ids array<int>, pieces long, pieces_encoded long")


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document encoded and decoded again; digests of both."""
    return encode_documents(common.read_table(spark, sf_dir, "documents"), keep_ids=False).drop("ids")
