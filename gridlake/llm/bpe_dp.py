"""BPE encoding by dynamic programming over prefixes, and decoding.

A text is cut into pieces by the vocabulary's public pattern; every piece is encoded
by itself.  For each prefix of a piece there is exactly one last token that byte-pair
merging can leave there.  A suffix automaton of all tokens is fed the piece byte by byte;
its suffix links give the tokens that end at a prefix's end, the longest first.  The one
that starts at the piece's beginning or is compatible with the last token of the prefix
before it is stored as the back-pointer.  Following the back-pointers gives the ids.  No
merge loop is run.

Defined results: a null text is empty and has no ids; the added token's string is cut
out first and gets its own id; bytes that are not UTF-8 are read as U+FFFD; repeated
rows, and rows without an id, give results of their own; an empty table gives no rows;
other columns are not read, whatever their names; a text is worked on as a whole, in time
that grows with its length.
"""

from __future__ import annotations

import hashlib
import json
import re
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridlake.llm.common import ship, text_spans

# The public piece pattern of this vocabulary.
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
# The characters that the pattern's white space stands for.
SPACE = "\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
#: Runs without white space (and one blank before them) or of white space alone: no piece
#: crosses their borders, so they are encoded, and remembered, by themselves.
CHUNKS = re.compile(rf" ?[^{SPACE}]+|[{SPACE}]+(?![^{SPACE}])|[{SPACE}]+").findall
#: Finds white space next to more of it, or at the end: only there is a blank no sure border.
PLAIN = re.compile(r"\s\s|\s\Z|\A\s").search
#: What a worker remembers at most; beyond it that memory starts anew.
MEMO_CHUNKS, MEMO_PAIRS = 500_000, 2_000_000
#: Longer pieces and chunks, in characters, aren't remembered.
SHORT = 48

_loaded: dict[tuple[type, str], Encoder] = {}


def printable_bytes() -> dict[str, int]:
    """The byte that each printable stand-in of a byte-level vocabulary means."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + k): b for k, b in enumerate(rest)}


class SuffixAutomaton:
    """All substrings of a set of tokens as states, linked to their longest suffixes of
    another state.  A token is the longest string of its state."""

    def __init__(self, tokens: dict[bytes, int]):
        self.step: list[dict[int, int]] = [{}]
        self.link, self.length, self.token = [-1], [0], [-1]
        for token, k in tokens.items():
            at = 0
            for byte in token:
                at = self._extend(at, byte)
            self.token[at] = k
        #: Length and token of every token that is a suffix of a state's longest string,
        #: the longest first; the suffix links reach all of them.
        self.suffixes: list[tuple[tuple[int, int], ...]] = [()] * len(self.link)
        for v in sorted(range(1, len(self.link)), key=self.length.__getitem__):
            own = ((self.length[v], self.token[v]),) if self.token[v] >= 0 else ()
            self.suffixes[v] = own + self.suffixes[self.link[v]] if own else self.suffixes[self.link[v]]

    def _state(self, length: int, link: int, step: dict[int, int]) -> int:
        self.step.append(step)
        self.link.append(link)
        self.length.append(length)
        self.token.append(-1)
        return len(self.link) - 1

    def _split(self, p: int, byte: int, q: int) -> int:
        """The state of the shorter strings of ``q`` that ``p`` leads to."""
        if self.length[q] == self.length[p] + 1:
            return q
        own = self._state(self.length[p] + 1, self.link[q], dict(self.step[q]))
        self.link[q] = own
        while p >= 0 and self.step[p].get(byte) == q:
            self.step[p][byte] = own
            p = self.link[p]
        return own

    def _extend(self, last: int, byte: int) -> int:
        known = self.step[last].get(byte)
        if known is not None:
            return self._split(last, byte, known)
        new, p = self._state(self.length[last] + 1, 0, {}), last
        while p >= 0 and byte not in self.step[p]:
            self.step[p][byte] = new
            p = self.link[p]
        if p >= 0:
            self.link[new] = self._split(p, byte, self.step[p][byte])
        return new


class Encoder(dict):
    """Maps a piece to its ids, packed as little-endian unsigned 32-bit integers."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        byte_of, vocab = printable_bytes(), spec["model"]["vocab"]
        self.added = {x["content"]: x["id"] for x in spec.get("added_tokens", [])}
        self.bytes_of = [b""] * (max([*vocab.values(), *self.added.values()]) + 1)
        for token, k in vocab.items():
            if token not in self.added:
                self.bytes_of[k] = bytes(byte_of[c] for c in token)
        for token, k in self.added.items():
            self.bytes_of[k] = token.encode()
        #: Of a pair: the rank of its merge and the id it gives; of an id: rank and halves.
        self.pair: dict[int, int] = {}
        self.rank = [-1] * len(self.bytes_of)
        self.left, self.right = [-1] * len(self.bytes_of), [-1] * len(self.bytes_of)
        for r, m in enumerate(spec["model"]["merges"]):
            a, b = m if isinstance(m, list) else m.split(" ")
            x, y, z = vocab[a], vocab[b], vocab[a + b]
            self.pair[x << 20 | y] = r
            self.rank[z], self.left[z], self.right[z] = r, x, y
        self.automaton = self._automaton({self.bytes_of[k]: k for t, k in vocab.items() if t not in self.added})
        self.cut = regex.compile(PIECES).findall
        self.at_added = regex.compile("(" + "|".join(map(regex.escape, sorted(self.added, key=len, reverse=True))) + ")") if self.added else None
        self.memo_pairs: dict[int, bool] = {}
        self.pieces: dict[str, bytes] = {}

    def _automaton(self, tokens: dict[bytes, int]) -> SuffixAutomaton | None:
        return SuffixAutomaton(tokens)

    @classmethod
    def load(cls, path: str):
        if (cls, path) not in _loaded:
            _loaded[cls, path] = cls(path)
        return _loaded[cls, path]

    def _compatible(self, a: int, b: int) -> bool:
        """Whether merging leaves ``a`` next to ``b``: no pair of pieces that face each
        other at the border, at a time when both exist, has a merge that comes first."""
        never = 1 << 30
        x, x_ends = a, never
        while x >= 0:
            y, y_ends = b, never
            while y >= 0:
                # both exist together only if each is made before the other is used up
                if self.rank[x] < y_ends and self.rank[y] <= x_ends:
                    r = self.pair.get(x << 20 | y)
                    # of equal ranks the leftmost merge is done first
                    if r is not None and r < x_ends and r <= y_ends:
                        return False
                y_ends, y = self.rank[y], self.left[y]
            x_ends, x = self.rank[x], self.right[x]
        return True

    def ids_of_piece(self, piece: bytes) -> list[int]:
        auto, pairs = self.automaton, self.memo_pairs
        step, link, length, suffixes = auto.step, auto.link, auto.length, auto.suffixes
        last: list[int] = [-1]
        state = matched = end = 0
        for byte in piece:
            end += 1
            following = step[state].get(byte)
            while following is None:  # fall back to the longest suffix that goes on
                state = link[state]
                matched = length[state]
                following = step[state].get(byte)
            state, matched = following, matched + 1
            # tokens that end here; the state's own only if it matched whole
            for size, k in suffixes[state if matched == length[state] else link[state]]:
                if size == end:
                    break
                key = last[end - size] << 20 | k
                fits = pairs.get(key)
                if fits is None:
                    fits = pairs[key] = self._compatible(last[end - size], k)
                if fits:
                    break
            last.append(k)
        out, at = [], len(piece)
        size = self.bytes_of
        while at:
            out.append(last[at])
            at -= len(size[last[at]])
        return out[::-1]

    def packed(self, chunk: str) -> bytes:
        """The ids of a chunk that no piece crosses the border of."""
        out, known = [], self.pieces
        for piece in self.cut(chunk):
            got = known.get(piece)
            if got is None:
                got = array("I", self.ids_of_piece(piece.encode())).tobytes()
                if len(piece) < SHORT:
                    known[piece] = got
            out.append(got)
        if len(known) >= MEMO_CHUNKS:
            known.clear()
        if len(self.memo_pairs) >= MEMO_PAIRS:
            self.memo_pairs.clear()
        return b"".join(out)

    def __missing__(self, word: str) -> bytes:
        got = self.packed(" " + word)
        if len(self) >= MEMO_CHUNKS:
            self.clear()
        if len(word) < SHORT:
            self[word] = got
        return got

    def _part(self, text: str) -> bytes:
        """The ids of a text without added tokens.  A blank before a character that is not
        white space always begins a piece, so the words behind blanks are independent."""
        if PLAIN(text):
            return b"".join([self[c[1:]] if c[0] == " " and not c[-1].isspace() else self.packed(c) for c in CHUNKS(text)])
        first, *words = text.split(" ")
        return b"".join((self.packed(first), *map(self.__getitem__, words)))

    def encode(self, text: str) -> bytes:
        """The ids of a text, packed."""
        if self.at_added is None or not any(t in text for t in self.added):
            return self._part(text)
        return b"".join(self.added[p].to_bytes(4, "little") if p in self.added else self._part(p) for p in self.at_added.split(text))

    def decode(self, packed: bytes) -> str:
        get = self.bytes_of.__getitem__
        return b"".join(map(get, np.frombuffer(packed, "<u4").tolist())).decode("utf-8", "replace")


def texts_of(col: pa.Array) -> Iterator[str]:
    """The texts of a column, null as empty, bytes that are no UTF-8 replaced."""
    data, offs = text_spans(col)
    raw = memoryview(data)
    for a, b in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True):
        yield str(raw[a:b], "utf-8", "replace")


def encode_documents(docs: DataFrame, tokenizer: str) -> DataFrame:
    """``doc_id, ids array<int>, decoded`` of every document."""
    ship(docs.sparkSession)

    def run(batches):
        enc = Encoder.load(tokenizer)
        for batch in batches:
            ids, back = [], []
            for text in texts_of(batch.column(1)):
                ids.append(np.frombuffer(enc.encode(text), "<i4"))
                back.append(enc.decode(ids[-1].tobytes()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, pa.list_(pa.int32())), pa.array(back, pa.string())], ["doc_id", "ids", "decoded"])

    return _plain(docs).mapInArrow(run, "doc_id long, ids array<int>, decoded string")


def digest_documents(docs: DataFrame, tokenizer: str) -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256`` of every document, without shipping ids."""
    ship(docs.sparkSession)

    def run(batches):
        enc = Encoder.load(tokenizer)
        for batch in batches:
            n, ids, back = [], [], []
            for text in texts_of(batch.column(1)):
                packed = enc.encode(text)
                n.append(len(packed) // 4)
                ids.append(hashlib.sha256(packed).hexdigest())
                back.append(hashlib.sha256(enc.decode(packed).encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(back, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return _plain(docs).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def _plain(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))


class LibraryEncoder(Encoder):
    """The same ids from a tokenizer library's merge loop, for operators that only need ids."""

    def __init__(self, path: str):
        import tiktoken

        super().__init__(path)
        taken = set(self.added.values())
        self.merge = tiktoken.Encoding("own", pat_str=PIECES, mergeable_ranks={b: k for k, b in enumerate(self.bytes_of) if k not in taken}, special_tokens={}).encode_ordinary

    def _automaton(self, tokens: dict[bytes, int]) -> None:
        return None

    def packed(self, chunk: str) -> bytes:
        return array("I", self.merge(chunk)).tobytes()
