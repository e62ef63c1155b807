"""Byte-level BPE encoding and decoding with the tokenizers library over Arrow batches.

The vocabulary is a file of token bytes and ranks. Every byte has a printable character in the byte table; tokens are
kept as strings over those characters, and merges follow from the ranks: a pair merges if its union is a token, in the
order of the union's rank. Decoding reverses the byte table. Text never leaves its row, so both directions are
embarrassingly parallel; the tokenizer is built once in each Python worker. The library itself cuts texts at the pattern's
matches: its letter and digit tables, not those of another regular-expression package, decide what a match is. Words that
come again are not cut and merged again: their ids are kept a while, under a pattern for which that can't change a match.
"""

from __future__ import annotations

import base64
import codecs
import os
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import prepare_workers, trim

_built: dict[str, tuple] = {}
#: Patterns without a match that goes on from a character to white space, and with no look behind: between a character that
#: is no white space and one that is, a text can be cut, and both parts give the ids that they give together.
APART = frozenset({r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"})
_WORD = re.compile("[ \t-\r]*[^ \t-\r]+|[ \t-\r]+")
#: Characters other than those of ``_WORD`` that some table of white space has or had, and control characters about them.
_UNSURE = re.compile("[\x00-\x08\x0e-\x1f\x7f-\xa0\u1680\u180e\u2000-\u200f\u2028-\u202f\u205f-\u206f\u3000\ufeff]")
#: Words, and characters of one, whose ids a process keeps at most; beyond, it forgets all and begins anew.
KEPT, KEPT_CHARS = 400_000, 64
#: New words that are encoded at once.
TOGETHER = 2_000
_SPACES = frozenset(" \t\n\x0b\x0c\r")
_ids: dict[str, dict[str, bytes]] = {}


def byte_table() -> list[str]:
    """The character of each byte: itself where it prints as one Latin-1 letter or sign, else the next free one from 256."""
    shown = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(256, 512))
    return [chr(b if b in shown else next(spare)) for b in range(256)]


def read_ranks(path: str) -> list[bytes]:
    """Token bytes by rank; ranks must be 0, 1, 2, ... without gaps."""
    with open(path, "rb") as f:
        pairs = [line.split() for line in f if line.strip()]
    out: list[bytes | None] = [None] * len(pairs)
    for token, rank in pairs:
        out[int(rank)] = base64.b64decode(token)
    if None in out:
        raise ValueError(f"{path}: ranks have gaps")
    return out  # type: ignore[return-value]


def merges_of(tokens: list[bytes]) -> list[tuple[bytes, bytes]]:
    rank = {t: i for i, t in enumerate(tokens)}
    found = []
    for t, i in rank.items():
        splits = [(rank[t[:k]], rank[t[k:]]) for k in range(1, len(t)) if t[:k] in rank and t[k:] in rank]
        found += [(i, *s) for s in sorted(splits)]
    return [(tokens[a], tokens[b]) for _, a, b in sorted(found)]


def tokenizer(path: str, pattern: str):
    """(tokenizers.Tokenizer, token bytes by id, their lengths), built once a process; what the pattern doesn't match gives no tokens."""
    key = f"{path}\0{pattern}"
    if key not in _built:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Regex, Tokenizer, models, pre_tokenizers

        tokens, chars = read_ranks(path), byte_table()
        show = lambda b: "".join(chars[x] for x in b)
        model = models.BPE(vocab={show(t): i for i, t in enumerate(tokens)}, merges=[(show(a), show(b)) for a, b in merges_of(tokens)], ignore_merges=True)
        out = Tokenizer(model)
        out.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.Split(Regex(pattern), "removed", invert=True), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        byte_of = {c: b for b, c in enumerate(chars)}
        by_id = [bytes(byte_of[c] for c in out.id_to_token(i)) for i in range(out.get_vocab_size(with_added_tokens=False))]
        _built[key] = (out, by_id, np.array([len(b) for b in by_id], dtype=np.int64))
    return _built[key]


def packed_ids(texts: list[str], path: str, pattern: str) -> list[bytes]:
    """Little-endian 32-bit ids of each text."""
    if pattern not in APART:
        return _library_ids(texts, path, pattern)
    words = [None if _UNSURE.search(t) else _WORD.findall(t) for t in texts]
    known, here = _ids.setdefault(f"{path}\0{pattern}", {}), set().union(*[w for w in words if w])
    new = list(here.difference(known))
    if len(known) + len(new) > KEPT:
        known.clear()
        new = list(here)
    known.update(_word_ids(new, path, pattern))
    whole = iter(_library_ids([t for t, w in zip(texts, words, strict=True) if w is None], path, pattern))
    out = [next(whole) if w is None else b"".join(map(known.__getitem__, w)) for w in words]
    for w in new:
        if len(w) > KEPT_CHARS:
            del known[w]
    return out


def _word_ids(words: list[str], path: str, pattern: str) -> Iterator[tuple[str, bytes]]:
    """(word, ids) of distinct words of texts. Those that begin with white space and end without are encoded end to end."""
    between = [w[0] in _SPACES and w[-1] not in _SPACES for w in words]
    alone = [w for w, b in zip(words, between, strict=True) if not b]
    yield from zip(alone, _library_ids(alone, path, pattern), strict=True)
    rest = [w for w, b in zip(words, between, strict=True) if b]
    size_of = tokenizer(path, pattern)[2]
    for some in (rest[i : i + TOGETHER] for i in range(0, len(rest), TOGETHER)):
        packed = _library_ids(["".join(some)], path, pattern)[0]
        ends = np.cumsum(size_of[np.frombuffer(packed, dtype="<u4")])
        cuts = np.searchsorted(ends, np.cumsum([len(w.encode()) for w in some]))
        at = [0, *((cuts + 1) * 4).tolist()]
        yield from ((w, packed[at[i] : at[i + 1]]) for i, w in enumerate(some))


def _library_ids(texts: list[str], path: str, pattern: str) -> list[bytes]:
    return [np.array(e.ids, dtype="<u4").tobytes() for e in tokenizer(path, pattern)[0].encode_batch_fast(texts, add_special_tokens=False)]


def _pieces(texts: list[str], limit: int) -> Iterator[list[int]]:
    """Indexes of successive texts of at most ``limit`` characters together, or of one longer text."""
    now, size = [], 0
    for i, t in enumerate(texts):
        if now and size + len(t) > limit:
            yield now
            now, size = [], 0
        now.append(i)
        size += len(t)
    if now:
        yield now


def encode(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", offsets: bool = False) -> DataFrame:
    """One row per row: (id_col, n_tokens, ids) and, if asked for, ``offsets``.

    ``ids`` is binary: 32-bit unsigned little-endian ids, four bytes each (``unpack_ids`` makes an array of them).
    ``offsets`` are byte ranges ``start, end, start, end, ...`` of each token in the UTF-8 text, also where a token ends
    inside a character. Null and empty texts give no tokens; null ids and repeated rows come back as they are; whole
    texts are encoded, whatever their length. Other columns are not read.
    """
    prepare_workers(docs.sparkSession)

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size_of = tokenizer(path, pattern)[2]
        for batch in batches:
            keys, texts = batch.column(0), [t or "" for t in batch.column(1).to_pylist()]
            for some in _pieces(texts, 1 << 18):
                ids = packed_ids([texts[i] for i in some], path, pattern)
                cols = [keys.slice(some[0], len(some)), pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(ids, pa.binary())]
                if offsets:
                    ids = [np.frombuffer(x, dtype="<u4") for x in ids]
                    ends = [np.cumsum(size_of[x]) for x in ids]
                    cols.append(pa.array([np.column_stack((e - size_of[x], e)).ravel() for x, e in zip(ids, ends, strict=True)], pa.list_(pa.int64())))
                yield pa.RecordBatch.from_arrays(cols, names=[id_col, "n_tokens", "ids"] + ["offsets"] * offsets)
            trim()

    key = docs.schema[id_col].dataType.simpleString()
    src = docs.select(F.col(id_col), F.col(text_col).cast("string").alias("strata_text"))
    return src.mapInArrow(work, f"`{id_col}` {key}, n_tokens long, ids binary" + ", offsets array<long>" * offsets)


def decode(rows: DataFrame, path: str, pattern: str, ids_col: str = "ids") -> DataFrame:
    """``rows`` with ``decoded`` (binary, exact) and without ``ids_col``: the bytes of the ids, through the reversed byte table.

    Null ids decode to empty bytes; an id outside the vocabulary raises. Other columns pass through untouched.
    """
    prepare_workers(rows.sparkSession)
    rest = [c for c in rows.columns if c not in (ids_col, "decoded")]
    fields = [rows.schema[c] for c in rest]

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by_id = tokenizer(path, pattern)[1]
        for batch in batches:
            out = [b"".join(map(by_id.__getitem__, np.frombuffer(x or b"", dtype="<u4").tolist())) for x in batch.column(len(rest)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(rest))), pa.array(out, pa.binary())], names=[*rest, "decoded"])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in fields), "decoded binary"])
    return rows.select(*(F.col(f"`{c}`") for c in rest), F.col(ids_col)).mapInArrow(work, schema)


def unpack_ids(col):
    """A packed id column as array<long>, with SQL functions only."""
    digits = F.hex(col)
    at = lambda i, k: F.substring(digits, i * 8 + 2 * k + 1, F.lit(2))
    return F.transform(F.sequence(F.lit(0), (F.length(col) / 4).cast("int") - 1), lambda i: F.conv(F.concat(*(at(i, k) for k in (3, 2, 1, 0))), 16, 10).cast("long"))


def stream_text(chunks: Iterable[Iterable[int]], by_id: list[bytes]) -> Iterator[str]:
    """Text of ids that arrive in pieces: a character split between tokens is held back until it is whole."""
    held = codecs.getincrementaldecoder("utf-8")(errors="replace")
    for ids in chunks:
        yield held.decode(b"".join(by_id[i] for i in ids))
    yield held.decode(b"", final=True)
