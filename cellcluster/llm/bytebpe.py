"""Byte-level BPE encoding and decoding in time linear in the text.

Each byte of a piece is mapped to the Latin-1 character of the same value, so a
string automaton over the vocabulary reports, for every position, the longest
token that starts there. The encoder takes longest tokens from left to right and
backs off to the next shorter prefix token whenever the last token and the new
one could not stand side by side in a merge result. Whether two tokens may be
neighbours depends on these two alone: undoing their last merges along the
touching edge must not meet a pair that would have merged earlier. Verdicts are
memoised, and a position from which no continuation exists is tried once only,
so the work is linear in the length of the piece.

Pieces are the matches of the pattern; each is encoded by itself, as merges never
cross pieces. A worker keeps the automaton; ids of pieces and verdicts on pairs
are remembered for one task, in tables with a bound in bytes.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Callable, Iterable
from itertools import accumulate, chain

import ahocorasick
import numpy as np
import regex
from pyspark.sql import DataFrame, SparkSession

from .common import add_columns, field, table

#: Bytes of pieces with their ids, and number of token pairs, that a task remembers.
MEMO_BYTES, MEMO_PAIRS = 64 << 20, 1 << 18
#: Pieces of more characters are not remembered.
LONG = 256


# Code points that the regex module, of a later Unicode version,
# counts as letters or digits and the tiktoken library does not.
LATER = (
    (0x558, 0x558), (0x58B, 0x58C), (0x88F, 0x88F), (0xC5C, 0xC5C), (0xCDC, 0xCDC), (0x208F, 0x208F), (0x209D, 0x209F), (0xA7CE, 0xA7CF),
    (0xA7D2, 0xA7D2), (0xA7D4, 0xA7D4), (0xA7DD, 0xA7DD), (0xA7E2, 0xA7E2), (0xA7F1, 0xA7F1), (0xAB6C, 0xAB6D), (0x107BB, 0x107BF), (0x10940, 0x10959),
    (0x10EC5, 0x10EC7), (0x10ED9, 0x10EEE), (0x11B0A, 0x11B0A), (0x11DB0, 0x11DDB), (0x11DE0, 0x11DE9), (0x11DF1, 0x11DF1), (0x1246F, 0x1246F),
    (0x12475, 0x1247F), (0x12550, 0x12686), (0x16EA0, 0x16EB8), (0x16EBB, 0x16ED3), (0x16FF2, 0x16FF6), (0x187F8, 0x187FF), (0x18CD6, 0x18CDA),
    (0x18D09, 0x18D20), (0x18D80, 0x18DF2), (0x18E00, 0x19191), (0x191A0, 0x191D2), (0x1B123, 0x1B128), (0x1B168, 0x1B168), (0x1D6A6, 0x1D6A6),
    (0x1DF1F, 0x1DF24), (0x1DF2B, 0x1DF81), (0x1DF90, 0x1DF96), (0x1DFCD, 0x1DFFF), (0x1E6C0, 0x1E6DE), (0x1E6E0, 0x1E6E2), (0x1E6E4, 0x1E6E5),
    (0x1E6E7, 0x1E6ED), (0x1E6F0, 0x1E6F4), (0x1E6FE, 0x1E6FF), (0x2B73A, 0x2B73F), (0x2B81E, 0x2B81E), (0x2CEA2, 0x2CEAD), (0x323B0, 0x33479),
    (0x3D000, 0x3FC3F),
)
_later = regex.compile("[" + "".join(f"{chr(a)}-{chr(b)}" for a, b in LATER) + "]")


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in (x.split() for x in lines if x.strip())}


def splitter(pattern: str) -> Callable[[str], list[str]]:
    """The pieces of a text. Texts of the basic plane go through ``re`` with its classes spelt out, others through ``regex``."""
    whole, plain = regex.compile(pattern), _spelt_out(pattern)
    astral = re.compile("[\U00010000-\U0010ffff]")

    def split(text: str) -> list[str]:
        if plain is not None and not astral.search(text):
            return plain.findall(text)
        if not _later.search(text):
            return [m[0] for m in whole.finditer(text)]
        # a private-use character has the class that the tiktoken library sees
        return [text[m.start() : m.end()] for m in whole.finditer(_later.sub("\ue000", text))]

    return split


def _spelt_out(pattern: str) -> re.Pattern | None:
    """The pattern for ``re`` with letters, digits and white space as ranges of the basic plane; None if it asks for more than those."""
    kinds = {r"\p{L}": _ranges(r"\p{L}"), r"\p{N}": _ranges(r"\p{N}"), r"\s": _ranges(r"\s")}
    out, inside = [], False
    for part in re.findall(r"\\[pP]\{[^}]*\}|\\.|[\[\]]|[^\\\[\]]+", pattern):
        if part in kinds:
            out.append(kinds[part] if inside else f"[{kinds[part]}]")
        elif part == r"\S" and not inside:
            out.append(f"[^{kinds[r'\s']}]")
        elif part[0] == "\\" and part[1].isalpha():
            return None
        else:
            inside = part == "[" or (inside and part != "]")
            out.append(part)
    if "(?i" in pattern or "[[" in pattern or "&&" in pattern:
        return None
    spelt = re.compile("".join(out))
    return None if spelt.groups else spelt


def _ranges(kind: str) -> str:
    one, ends = regex.compile(kind), []
    for c in chain(range(0xD800), range(0xE000, 0x10000)):
        if one.match(chr(c)) and not _later.match(chr(c)):
            if ends and ends[-1][1] == c - 1:
                ends[-1][1] = c
            else:
                ends.append([c, c])
    return "".join(f"\\u{a:04x}-\\u{b:04x}" for a, b in ends)


class _Recent(dict):
    """Values by key, made where they are missing, in two generations: the older goes when the younger is full."""

    def __init__(self, make: Callable, most: int, cost: Callable):
        super().__init__()
        self.make, self.most, self.cost, self.held, self.older = make, most, cost, 0, {}

    def __missing__(self, key):
        value = self.older.get(key)
        if value is None:
            value = self.make(key)
        cost = self.cost(key, value)
        if cost:
            self.held += cost
            if self.held > self.most:
                self.older, self.held = dict(self), cost
                self.clear()
            self[key] = value
        return value

    def forget(self) -> None:
        self.clear()
        self.older, self.held = {}, 0


class ByteBpe:
    """Exact merge results of a vocabulary of ranks."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks = ranks
        self.split = splitter(pattern)
        self.bytes_of = {i: t for t, i in ranks.items()}
        self._pairs = _Recent(lambda pair: self._adjacent(pair >> 32, pair & 0xFFFFFFFF), MEMO_PAIRS // 2, lambda pair, verdict: 1)
        # about what a string, a tuple and an entry of a table take
        self._pieces = _Recent(lambda piece: self.encode_piece(piece.encode("utf-8")), MEMO_BYTES // 2, lambda piece, ids: 200 + 2 * len(piece) + 8 * len(ids) if len(piece) <= LONG else 0)
        self._size = {i: len(t) for t, i in ranks.items()}
        self._widest = max(map(len, ranks))
        self._tokens = ahocorasick.Automaton()
        for token, rank in ranks.items():
            self._tokens.add_word(token.decode("latin-1"), rank)
        self._tokens.make_automaton()
        # the longest token that is a proper prefix of a token
        self._shorter: dict[int, int] = {}
        for token, rank in ranks.items():
            for n in range(len(token) - 1, 0, -1):
                if token[:n] in ranks:
                    self._shorter[rank] = ranks[token[:n]]
                    break
        # the two tokens whose merge makes a token; a byte is made of none
        self._halves: dict[int, tuple[int, int]] = {}
        self._joined: dict[tuple[int, int], int] = {}
        for token, rank in sorted(ranks.items(), key=lambda x: x[1]):
            if len(token) == 1:
                continue
            for n in range(1, len(token)):
                left, right = ranks.get(token[:n]), ranks.get(token[n:])
                if left is not None and right is not None and left < rank and right < rank and self._adjacent(left, right):
                    self._halves[rank] = (left, right)
                    self._joined[left, right] = rank
                    break

    def _adjacent(self, left: int, right: int) -> bool:
        """Whether the tokens can follow each other in a merge result.

        The merges at the touching edge are undone, the latest first. A pair
        that merges into a token older than the merge undone before it would
        have been joined instead.
        """
        bound = 1 << 62
        while True:
            merged = self._joined.get((left, right))
            if merged is not None and merged < bound:
                return False
            a, b = self._halves.get(left), self._halves.get(right)
            if a is None and b is None:
                return True
            if b is None or (a is not None and left > right):
                bound, left = left, a[1]
            else:
                bound, right = right + 1, b[0]

    def forget(self) -> None:
        """Drop what was remembered; the tables of the vocabulary stay."""
        self._pairs.forget()
        self._pieces.forget()

    def encode_piece(self, piece: bytes) -> tuple[int, ...]:
        whole = self.ranks.get(piece)
        if whole is not None:
            return (whole,)
        text, n = piece.decode("latin-1"), len(piece)
        size, adjacent, shorter = self._size, self._pairs, self._shorter
        # the longest tokens from left to right, up to the first that cannot follow the one before it
        out = [token for _, token in self._tokens.iter_long(text)]
        if sum(map(size.__getitem__, out)) != n:
            raise ValueError("the vocabulary lacks a byte")
        before, good = out[0], 1
        for token in out[1:]:
            if not adjacent[before << 32 | token]:
                break
            before = token
            good += 1
        else:
            return tuple(out)
        token = shorter.get(out[good])
        del out[good:]
        ends = [0, *accumulate(map(size.__getitem__, out))]
        at = ends.pop()
        longest, widest = self._tokens.longest_prefix, self._widest
        dead = bytearray(n + 1)
        while True:
            while token is not None:
                end = at + size[token]
                if not dead[end] and (not out or adjacent[out[-1] << 32 | token]):
                    break
                token = shorter.get(token)
            if token is not None:
                out.append(token)
                ends.append(at)
                at = end
                if at == n:
                    return tuple(out)
                token = self._longest(text, at, longest(text[at : at + widest]))
                continue
            # nothing fits here after the last token: give that one up
            dead[at] = 1
            token = shorter.get(out.pop())
            at = ends.pop()

    def _longest(self, text: str, at: int, n: int) -> int:
        # the trie also holds prefixes of tokens that are no tokens themselves
        known = self._tokens
        token = known.get(text[at : at + n], None)
        while token is None:
            n -= 1
            token = known.get(text[at : at + n], None)
        return token

    def encode(self, text: str) -> list[int]:
        return list(chain.from_iterable(map(self._pieces.__getitem__, self.split(text))))

    def decode(self, ids: Iterable[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


#: The last encoder that this worker process has built.
_built: dict[tuple[str, str], ByteBpe] = {}


def add_tokens(docs: DataFrame, ranks_path: str, pattern: str, text: str = "text", ids: str | None = "ids", digests: bool = False, keep: list[str] | None = None) -> DataFrame:
    """``docs`` with n_tokens and the token ids, or digests of them and of the decoded bytes.

    The whole text is encoded, without special tokens. Null counts as empty: no
    tokens. The vocabulary file has a fixed size and is read by the driver once.
    """
    shared = docs.sparkSession.sparkContext.broadcast(read_ranks(ranks_path))
    fields = [field("n_tokens", "bigint")]
    fields += [field(ids, "array<int>")] if ids else []
    fields += [field("ids_sha256", "string"), field("decoded_sha256", "string")] if digests else []

    def make():
        bpe = _built.get((ranks_path, pattern))
        if bpe is None:
            _built.clear()
            bpe = _built[ranks_path, pattern] = ByteBpe(shared.value, pattern)
        name = {i: str(i) for i in bpe.bytes_of}.__getitem__ if digests else None

        def work(texts):
            for raw in texts:
                found = bpe.encode(raw.decode("utf-8", "replace"))
                row = (len(found),) + ((np.array(found, np.int32),) if ids else ())
                if digests:
                    row += (hashlib.sha256(" ".join(map(name, found)).encode()).hexdigest(), hashlib.sha256(bpe.decode(found)).hexdigest())
                yield row

        work.done = bpe.forget
        return work

    return add_columns(docs, text, fields, make, keep)


def production() -> tuple[str, str]:
    """Vocabulary file and piece pattern of the public tokenizers installed here."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def op10_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return add_tokens(docs, *production(), ids=None, digests=True, keep=["doc_id"])
