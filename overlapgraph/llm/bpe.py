"""Byte-level BPE encoding by dynamic programming over prefixes, and decoding.

For every prefix of a piece of text there is exactly one token that ends its encoding. It is found
among the vocabulary entries that are suffixes of the prefix (an automaton with suffix links
lists them, all prefixes in one pass): the entry t of length l is the one if t may follow
the last token of the prefix that is l shorter. Two tokens may follow each other if the merges
that make them, undone from the latest to the earliest, never meet a merge across their border that would have come first.
Back-pointers then give the ids, the same that the merge procedure gives, without its queue.
"""

from __future__ import annotations

import hashlib
import json
import re
import sys
import unicodedata
from array import array
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textvec as tv
from .common import text_batches, text_of

#: Pieces of text whose ids a worker remembers; the memory is emptied when it is full.
CACHE_PIECES = 150_000
#: Pairs of tokens whose compatibility a worker remembers.
CACHE_PAIRS = 250_000
#: Longer pieces are not remembered.
CACHE_CHARS = 64
#: Stands between pieces in the automaton's input, whose letters are bytes; not a byte itself.
SEPARATOR = "\u0100"


def byte_alphabet() -> dict[str, int]:
    """The printable character that stands for each byte in byte-level vocabularies (fixed rule)."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out = {chr(b): b for b in plain}
    rest = [b for b in range(256) if b not in set(plain)]
    return out | {chr(256 + i): b for i, b in enumerate(rest)}


def _category_class(*kinds: str, last: int = sys.maxunicode) -> str:
    """A character class of all code points up to ``last`` of the given general categories."""
    out, start = [], None
    for c in range(last + 2):
        inside = c <= last and unicodedata.category(chr(c)).startswith(kinds)
        if inside and start is None:
            start = c
        elif not inside and start is not None:
            out.append(f"\\U{start:08x}-\\U{c - 1:08x}")
            start = None
    return "".join(out)


#: White space as the Unicode property has it (fixed values).
_SPACE = "\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"


#: Code points beyond the first plane; classes that hold such ranges test them one by one at the end of every word.
_BEYOND = re.compile("[\U00010000-\U0010ffff]")


def piece_pattern(last: int = sys.maxunicode) -> re.Pattern:
    """The pattern that cuts text of code points up to ``last`` before merging: contractions, words, numbers, signs, blanks."""
    letter, number = _category_class("L", last=last), _category_class("N", last=last)
    # fixed pattern, the same as in the vocabulary's description
    return re.compile(f"'s|'t|'re|'ve|'m|'ll|'d| ?[{letter}]+| ?[{number}]+| ?[^{_SPACE}{letter}{number}]+|[{_SPACE}]+(?![^{_SPACE}])|[{_SPACE}]+")


class PrefixEncoder:
    """Encoder and decoder of one vocabulary file; needs only its JSON text."""

    def __init__(self, text: str):
        spec = json.loads(text)
        alphabet = byte_alphabet()
        vocab = spec["model"]["vocab"]
        as_bytes = {t: bytes(alphabet[c] for c in t) for t in vocab if all(c in alphabet for c in t)}
        self.special = {a["content"]: a["id"] for a in spec.get("added_tokens") or []}
        self.token_bytes: dict[int, bytes] = {i: as_bytes.get(t, t.encode()) for t, i in vocab.items()}
        self.token_bytes |= {i: t.encode() for t, i in self.special.items()}
        self.rank: dict[int, int] = {}  # by left << 32 | right
        self.parts: dict[int, tuple[int, int]] = {}
        self.made: dict[int, int] = {}
        for r, pair in enumerate(spec["model"]["merges"]):
            a, b = pair.split(" ") if isinstance(pair, str) else pair
            left, right, new = vocab[a], vocab[b], vocab[a + b]
            self.rank.setdefault(left << 32 | right, r)
            if new not in self.parts:
                self.parts[new], self.made[new] = (left, right), r
        self.automaton = ahocorasick.Automaton()
        for t, i in vocab.items():
            if t not in self.special and t in as_bytes:
                raw = as_bytes[t]
                self.automaton.add_word(raw.decode("latin-1"), (i, len(raw)))
        self.automaton.make_automaton()
        self.pairs: dict[int, bool] = {}  # by left << 32 | right
        self.pattern, self.plain, self.ascii = piece_pattern(), piece_pattern(0xFFFF), piece_pattern(0x7F)
        self.cut = re.compile("(" + "|".join(re.escape(s) for s in sorted(self.special, key=len, reverse=True)) + ")") if self.special else None
        self.cache: dict[str, bytes] = {}

    def may_follow(self, left: int, right: int) -> bool:
        """Whether the border between two tokens survives all merges of their joint text.

        The tokens on both sides of the border are undone, the later merge first. At each stage
        the two tokens at the border stood side by side from the later of their own merges until
        the merge that was just undone, and in that time no merge may have joined them.
        """
        key = left << 32 | right
        known = self.pairs.get(key)
        if known is not None:
            return known
        until = len(self.rank) + 1
        inclusive = False  # on the right a merge of the same rank further left would come first
        ok = True
        while True:
            r = self.rank.get(left << 32 | right)
            if r is not None and (r < until or (inclusive and r == until)):
                ok = False
                break
            made_l, made_r = self.made.get(left, -1), self.made.get(right, -1)
            if made_l < 0 and made_r < 0:
                break
            # equal ranks are merged from left to right, so the right one is undone first
            if made_l > made_r:
                until, inclusive, left = made_l, False, self.parts[left][1]
            else:
                until, inclusive, right = made_r, True, self.parts[right][0]
        if len(self.pairs) >= CACHE_PAIRS:
            self.pairs.clear()
        self.pairs[key] = ok
        return ok

    def piece(self, raw: bytes) -> list[int]:
        """Ids of one piece, by the last token of each of its prefixes."""
        return self._pieces([raw])[0].tolist() if raw else []

    def _pieces(self, raws: list[bytes]) -> list[array]:
        """Ids of pieces that are not empty; one pass of the automaton over all, with a sign between them that no token holds."""
        joined = SEPARATOR.join([raw.decode("latin-1") for raw in raws])
        # last token of the prefix that ends here: none yet, or the piece's start
        last, width = [-1] * (len(joined) + 1), [0] * (len(joined) + 1)
        at = 0
        for raw in raws:
            last[at] = -2
            at += len(raw) + 1
        may = self.may_follow
        known = self.pairs.get
        for end, (token, size) in self.automaton.iter(joined):
            end += 1
            if last[end] != -1:
                continue
            prev = last[end - size]
            if prev < 0:
                if prev == -2:
                    last[end], width[end] = token, size
                continue
            ok = known(prev << 32 | token)
            if may(prev, token) if ok is None else ok:
                last[end], width[end] = token, size
        out, at = [], 0
        for raw in raws:
            start, n, ids = at, at + len(raw), array("I")
            at = n + 1
            while n > start:
                if not width[n]:
                    raise ValueError("the vocabulary has no token for some byte")
                ids.append(last[n])
                n -= width[n]
            ids.reverse()
            out.append(ids)
        return out

    def _learn(self, new: list[str]) -> dict[str, bytes]:
        """Ids of pieces that are not remembered; the shorter ones are from now on."""
        out = {}
        for text, ids in zip(new, self._pieces([t.encode("utf-8") for t in new]), strict=True):
            if sys.byteorder == "big":
                ids.byteswap()
            out[text] = ids.tobytes()
        if len(self.cache) + len(out) > CACHE_PIECES:
            self.cache.clear()
        self.cache |= {t: p for t, p in out.items() if len(t) <= CACHE_CHARS} if len(out) <= CACHE_PIECES else {}
        return out

    def encode_packed(self, text: str) -> bytes:
        """Ids of a whole text as little-endian unsigned 32-bit integers."""
        out = []
        pattern = self.ascii if text.isascii() else self.pattern if _BEYOND.search(text) else self.plain
        for i, part in enumerate(self.cut.split(text) if self.cut else [text]):
            if i % 2:
                out.append(self.special[part].to_bytes(4, "little"))
            elif part:
                cut = pattern.findall(part)
                got = list(map(self.cache.get, cut))
                if None in got:
                    new = self._learn(list({p for p, g in zip(cut, got, strict=True) if g is None}))
                    got = [new[p] if g is None else g for p, g in zip(cut, got, strict=True)]
                out += got
        return b"".join(out)

    def encode(self, text: str) -> list[int]:
        return unpack(self.encode_packed(text))

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.token_bytes.__getitem__, ids)).decode("utf-8", "replace")


def unpack(packed: bytes) -> list[int]:
    ids = array("I")
    ids.frombytes(packed)
    if sys.byteorder == "big":
        ids.byteswap()
    return ids.tolist()


_encoders: dict[str, PrefixEncoder] = {}


def encoder_of(spec: str) -> PrefixEncoder:
    """One encoder per worker process and vocabulary."""
    key = hashlib.sha256(spec.encode()).hexdigest()
    if key not in _encoders:
        _encoders[key] = PrefixEncoder(spec)
    return _encoders[key]


def read_spec(path: str) -> str:
    """The vocabulary file, read by the driver; workers get its text by broadcast."""
    with open(path, encoding="utf-8") as f:
        return f.read()


def encode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True) -> DataFrame:
    """One row per input row: id, n_tokens, ids_sha256, decoded_sha256 and, if asked, the ids.

    Null and empty texts have no tokens. The strings of special tokens in a text become these
    tokens. Repeated rows get equal results; other columns are not read, so no name can clash.
    """
    spark: SparkSession = docs.sparkSession
    spec = spark.sparkContext.broadcast(read_spec(path))  # the vocabulary: fixed, about two megabytes

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = encoder_of(spec.value)
        for batch in tv.pieces(batches):
            n, ids_hash, text_hash, ids = [], [], [], []
            for text in batch.column(1).to_pylist():
                packed = coder.encode_packed(text)
                back = coder.decode(unpack(packed))
                n.append(len(packed) // 4)
                ids_hash.append(hashlib.sha256(packed).hexdigest())
                text_hash.append(hashlib.sha256(back.encode("utf-8")).hexdigest())
                if with_ids:
                    ids.append(unpack(packed))
            out = [batch.column(0), pa.array(n, pa.int64()), pa.array(ids_hash, pa.string()), pa.array(text_hash, pa.string())]
            yield pa.RecordBatch.from_arrays([*out, pa.array(ids, pa.list_(pa.int32()))] if with_ids else out, names)
        coder.cache.clear()
        tv.release()

    fields = [T.StructField("id", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())]
    fields += [T.StructField("ids", T.ArrayType(T.IntegerType()))] * with_ids
    names = [f.name for f in fields]
    out = text_batches(docs).select(F.col(id_col).cast("long").alias("id"), text_of(text_col).alias("text")).mapInArrow(run, T.StructType(fields))
    return out.withColumnRenamed("id", id_col)
