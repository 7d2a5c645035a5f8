"""Byte-level BPE encoding and decoding with the tokenizers library, over Arrow batches.

A rank file gives byte strings and their ids. ``ByteBPE`` maps bytes to printable characters, derives the merge
list from the ranks and hands both to ``tokenizers.models.BPE``. Text is cut by the pre-tokenising pattern; each
distinct piece is encoded once per worker by the library and kept in a bounded cache, since most pieces of a
corpus repeat. Offsets come as byte spans, and as character spans where asked: a token that holds part of a
character gets the span of the whole character. Decoding reverses the byte table over the whole id list, so that
characters split between tokens come back whole.
"""

from __future__ import annotations

import array
import base64
import hashlib
import os
import re
from collections.abc import Iterable, Iterator
from itertools import islice

import pyarrow as pa
import regex
from pyspark import SparkFiles
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_of, lean, slices, text_of

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
#: Distinct pieces whose ids a worker keeps; about 100 bytes each.
_CACHE_PIECES = 400_000


def byte_characters() -> list[str]:
    """A printable character for each byte: itself where printable, the rest from U+0100 on in order."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(0x100, 0x200))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


def load_ranks(path: str) -> dict[bytes, int]:
    """Byte strings and ids from a file of base64 strings and numbers."""
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}


def merges_of(ranks: dict[bytes, int]) -> list[tuple[bytes, bytes]]:
    """The merge that made each string of several bytes: the two parts left when only lower ranks merge."""
    out = []
    for whole, rank in sorted(((w, r) for w, r in ranks.items() if len(w) > 1), key=lambda x: x[1]):
        parts = [whole[i : i + 1] for i in range(len(whole))]
        while len(parts) > 2:
            best = min(range(len(parts) - 1), key=lambda i: ranks.get(parts[i] + parts[i + 1], rank))
            if ranks.get(parts[best] + parts[best + 1], rank) >= rank:
                break
            parts[best : best + 2] = [parts[best] + parts[best + 1]]
        if len(parts) == 2:
            out.append((parts[0], parts[1]))
    return out


def latin_pattern(pattern: str) -> re.Pattern | None:
    """``pattern`` for texts of characters up to U+00FF only, in the faster standard module: its Unicode classes are
    spelt out for these. None if the pattern has other escapes."""
    latin = [chr(c) for c in range(256)]
    inner = {e: "".join(re.escape(c) for c in latin if regex.match(e, c)) for e in (r"\p{L}", r"\p{N}", r"\s")}
    out, at, depth = [], 0, False
    while at < len(pattern):
        found = next((e for e in (*inner, r"\S") if pattern.startswith(e, at)), None)
        if found == r"\S" and not depth:
            out.append(f"[^{inner[r'\s']}]")
        elif found and found != r"\S":
            out.append(inner[found] if depth else f"[{inner[found]}]")
        elif pattern[at] == "\\":
            return None
        else:
            depth = {"[": True, "]": False}.get(pattern[at], depth)
            out.append(pattern[at])
        at += len(found or " ")
    return re.compile("".join(out))


class ByteBPE:
    """Encoder and decoder for one rank file and one pre-tokenising pattern."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        from tokenizers import Tokenizer, models

        self.characters = dict(enumerate(byte_characters()))
        named = self.named
        vocab = {named(b): i for b, i in ranks.items()}
        self.model = Tokenizer(models.BPE(vocab, [(named(a), named(b)) for a, b in merges_of(ranks)], cache_capacity=0))
        self.split_any, latin = regex.compile(pattern).findall, latin_pattern(pattern)
        self.split_latin = latin.findall if latin else None
        self.strings: list[bytes] = [b""] * (max(ranks.values()) + 1)
        for b, i in ranks.items():
            self.strings[i] = b
        self.decimal = [str(i) for i in range(len(self.strings))]
        self.cache: dict[str, bytes] = {}

    def named(self, raw: bytes) -> str:
        """The printable form of a byte string."""
        return raw.decode("latin-1").translate(self.characters)

    def split(self, text: str) -> list[str]:
        """The matches of the pattern."""
        if self.split_latin:
            try:
                text.encode("latin-1")
                return self.split_latin(text)
            except UnicodeEncodeError:
                pass
        return self.split_any(text)

    def ids(self, text: str) -> array.array:
        """The ids of a text, 4 bytes each."""
        pieces, cache, out = self.split(text), self.cache, array.array("I")
        try:
            out.frombytes(b"".join(map(cache.__getitem__, pieces)))
        except KeyError:
            if len(cache) > _CACHE_PIECES:
                for old in list(islice(cache, _CACHE_PIECES // 2)):
                    del cache[old]
            new = [p for p in dict.fromkeys(pieces) if p not in cache]
            found = self.model.encode_batch_fast([self.named(p.encode()) for p in new], add_special_tokens=False)
            cache.update(zip(new, (array.array("I", x.ids).tobytes() for x in found)))
            out.frombytes(b"".join(map(cache.__getitem__, pieces)))
        return out

    def decode(self, ids: Iterable[int]) -> bytes:
        return b"".join(map(self.strings.__getitem__, ids))

    def byte_offsets(self, ids: Iterable[int]) -> list[int]:
        """Where each token ends, in bytes."""
        ends, at = [], 0
        for i in ids:
            at += len(self.strings[i])
            ends.append(at)
        return ends

    def char_offsets(self, text: str, ids: Iterable[int]) -> list[tuple[int, int]]:
        """The span of characters that each token touches."""
        owner = [k for k, c in enumerate(text) for _ in c.encode()]
        spans, at = [], 0
        for end in self.byte_offsets(ids):
            spans.append((owner[at], owner[end - 1] + 1))
            at = end
        return spans


_LOADED: dict[tuple, ByteBPE] = {}


def codec(path: str, pattern: str) -> ByteBPE:
    """The codec of a rank file, loaded once per worker."""
    if (path, pattern) not in _LOADED:
        local = path if os.path.exists(path) else SparkFiles.get(os.path.basename(path))
        _LOADED[path, pattern] = ByteBPE(load_ranks(local), pattern)
    return _LOADED[path, pattern]


class _Lists:
    """Lists of 4-byte integers as one buffer of values and one of offsets."""

    def __init__(self):
        self.values, self.offsets = array.array("i"), array.array("i", [0])

    def add(self, items: array.array) -> None:
        self.values.frombytes(items.tobytes())
        self.offsets.append(len(self.values))

    def column(self) -> pa.Array:
        values, offsets = (pa.Array.from_buffers(pa.int32(), len(a), [None, pa.py_buffer(a.tobytes())]) for a in (self.values, self.offsets))
        return pa.ListArray.from_arrays(offsets, values)


def encode_decode(docs: DataFrame, rank_path: str, pattern: str, *, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False, with_offsets: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256, round_trip for each row; ids and char_starts, char_ends on request.

    Each match of the pattern is encoded on its own and no special token is added. Null texts count as empty: no
    tokens, the digests of the empty string. Rows are independent, so repeated rows repeat and an empty table gives
    an empty result; texts are encoded whole, and a worker holds the ids of about 1 MB of text (or of one longer
    text) at a time. ``rank_path`` is a file that each worker can open (or one shipped by
    ``addFile``).
    """
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, round_trip boolean"
    schema += ", ids array<int>" * with_ids + ", char_starts array<int>, char_ends array<int>" * with_offsets

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe, sha = codec(rank_path, pattern), hashlib.sha256
        for batch in (part for whole in batches for part in slices(whole, 1)):
            n, hashes, back_hashes, equal = [], [], [], []
            ids, starts, ends = _Lists(), _Lists(), _Lists()
            for x in batch.column(1):
                text = x.as_py()
                found = bpe.ids(text)
                back, raw = bpe.decode(found), text.encode()
                n.append(len(found))
                hashes.append(sha(" ".join(map(bpe.decimal.__getitem__, found)).encode()).hexdigest())
                back_hashes.append(sha(back).hexdigest())
                equal.append(back == raw)
                if with_ids:
                    ids.add(found)
                if with_offsets:
                    spans = bpe.char_offsets(text, found)
                    starts.add(array.array("i", (a for a, _ in spans)))
                    ends.add(array.array("i", (b for _, b in spans)))
            arrays = [batch.column(0), pa.array(n, pa.int64()), pa.array(hashes, pa.string()), pa.array(back_hashes, pa.string()), pa.array(equal, pa.bool_())]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "round_trip"]
            if with_ids:
                arrays.append(ids.column())
                names.append("ids")
            if with_offsets:
                arrays += [starts.column(), ends.column()]
                names += ["char_starts", "char_ends"]
            yield pa.RecordBatch.from_arrays(arrays, names=names)

    return docs.select(id_of(id_col).alias("doc_id"), text_of(text_col).alias("text")).mapInArrow(lean(run), schema)


def encode_ids(docs: DataFrame, rank_path: str, pattern: str, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and ids: the form to store."""
    return encode_decode(docs, rank_path, pattern, id_col=id_col, text_col=text_col, with_ids=True).select("doc_id", "ids")


def decode_ids(rows: DataFrame, rank_path: str, pattern: str, *, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """doc_id, bytes and text of each id list; bytes that aren't UTF-8 show as U+FFFD in the text only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = codec(rank_path, pattern)
        for batch in (whole.slice(i, 200) for whole in batches for i in range(0, whole.num_rows, 200)):
            raw = [bpe.decode(x) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(raw, pa.binary()), pa.array([b.decode("utf-8", "replace") for b in raw], pa.string())], names=["doc_id", "bytes", "text"])

    ids = F.coalesce(F.col(f"`{ids_col}`").cast("array<int>"), F.array().cast("array<int>"))
    return rows.select(id_of(id_col).alias("doc_id"), ids.alias("ids")).mapInArrow(lean(run), "doc_id long, bytes binary, text string")
