"""Token counts and token ids of whole texts, by the tokenizers library.

A byte-level tokenizer's pattern never matches across a change from a visible character to white space, nor from a letter
or digit to a mark, and looks no further back.  Texts are cut there into pieces, a run of white space with the run of
letters after it, or marks, so that a piece's ids are the same in any text.  Pieces are found and hashed (64 bits) with array operations over a whole slice of
texts; a table of SLOTS places remembers the value of the last piece of each place, and only pieces that it doesn't hold go
to the library, each once a slice, in batches balanced by bytes.  A worker thus holds a table of fixed size and one
slice of at most WINDOW_BYTES (or one longer piece).  A longer piece than LONG_BYTES is a single run without such a place; its merges may span it all, so that no
method that gives the library's ids can cut it, and the library gets it whole.

Vocabularies of another kind (other patterns, normalisers, strings that take white space with them, sentencepiece
models) get whole texts.
"""

from __future__ import annotations

import json
import os
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import held_by_worker, slices, span_hashes, text_buffer, tidy

VOCABULARY = "byte_bpe_50k.json"
TOKEN_LIMIT = 512
#: Places of a worker's table (14 bytes each at most), ids that its store holds, bytes of the longest piece remembered.
SLOT_BITS = 21
STORE_IDS = 8 << 20
REMEMBERED_BYTES = 64
LONG_BYTES = 4096
BATCH_BYTES = 1 << 13
WINDOW_BYTES = 1 << 18

_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
_VISIBLE = np.zeros(256, bool)
_VISIBLE[33:127] = True
_LETTER = np.zeros(256, bool)
_LETTER[48:58] = _LETTER[65:91] = _LETTER[97:123] = True
_MARK = _VISIBLE & ~_LETTER


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


_SOLID = _VISIBLE | (np.arange(256) >= 128)


def piece_starts(data: np.ndarray, offsets: np.ndarray, marks: bool = True) -> np.ndarray:
    """Where pieces start in concatenated texts: at each text, at ASCII white space after a visible character, and with
    `marks` at an ASCII mark after an ASCII letter or digit or a letter of the Latin-1 supplement.

    After a byte of a longer character a cut at white space is left out if that could be a space of its own.
    """
    flags = np.zeros(len(data), bool)
    if len(data):
        flags[1:] = _BLANK[data[1:]] & _SOLID[data[:-1]]
        wide = np.flatnonzero(flags[1:] & (data[:-1] >= 128)) + 1
        if len(wide):
            last, middle, first = data[wide - 1], data[wide - 2], data[np.maximum(wide - 3, 0)]
            space = (middle == 0xC2) & np.isin(last, (0x85, 0xA0))
            space |= (first == 0xE1) & np.isin(middle, (0x9A, 0xA0)) | (first == 0xE3) & (middle == 0x80) & (last == 0x80)
            space |= (first == 0xE2) & (middle == 0x80) & ((last < 0x90) | (last >= 0xA8) & (last < 0xB0)) | (first == 0xE2) & (middle == 0x81)
            flags[wide[space]] = False
        if marks:
            at = np.flatnonzero(_MARK[data[1:]]) + 1
            last = data[at - 1]
            latin = (data[np.maximum(at - 2, 0)] == 0xC3) & (last >= 0x80) & (last != 0x97) & (last != 0xB7)
            flags[at[_LETTER[last] | latin]] = True
        flags[offsets[:-1][np.diff(offsets) > 0]] = True
    return np.flatnonzero(flags)


_ONE_BLANK = re.compile(rb" [^\s]{1,%d}" % LONG_BYTES).fullmatch


class Library:
    """The installed library behind a vocabulary file, and what its pattern allows."""

    def __init__(self, path: str):
        self.cuts, self.added = False, []
        if path.endswith(".model"):
            import sentencepiece

            model = sentencepiece.SentencePieceProcessor(model_file=path)
            self.size = model.vocab_size()
            self.encode = lambda texts: model.encode(texts, num_threads=1)
            return
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # tasks are the parallel part; threads of the library would each hold memory
        from tokenizers import Tokenizer

        library = Tokenizer.from_file(path)
        library.no_truncation()
        library.no_padding()
        self.size = library.get_vocab_size()
        self.encode = lambda texts: [e.ids for e in library.encode_batch_fast(texts, add_special_tokens=False)]
        told = json.loads(library.to_str())
        kind, added = told["pre_tokenizer"] or {}, told["added_tokens"]
        plain = all(not (x["lstrip"] or x["rstrip"] or x["single_word"] or any(map(str.isspace, x["content"]))) for x in added)
        self.cuts = told["normalizer"] is None and kind.get("type") == "ByteLevel" and kind.get("use_regex", True) and not kind.get("add_prefix_space") and plain
        self.opens = np.zeros(self.size, bool)
        self.opens[[k for word, k in library.get_vocab().items() if word.startswith("Ġ")]] = True
        self.added = [x["content"].encode() for x in added]


class PieceEncoder:
    """Encodes slices of texts; with `ids` it gives ids, else counts alone."""

    def __init__(self, path: str, ids: bool):
        self.library, self.ids = Library(path), ids
        self.kind = np.dtype("<u2" if self.library.size <= 1 << 16 else "<u4")
        self.keys = np.zeros(1 << SLOT_BITS, np.uint64)
        self.counts = np.zeros(1 << SLOT_BITS, np.uint16)
        self.forget()

    def forget(self) -> None:
        self.keys[:] = 0
        if self.ids:
            self.at = np.zeros(1 << SLOT_BITS, np.int32)
            self.store, self.used = np.zeros(STORE_IDS, self.kind), 0

    def encoded(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids, number of ids of each piece)."""
        counts, parts = np.zeros(len(pieces), np.int64), [np.zeros(0, self.kind)] * len(pieces)
        simple = np.array([self.library.cuts and x[0] == 32 and _ONE_BLANK(x) is not None for x in pieces], bool)
        start, size, chosen = 0, 0, np.flatnonzero(simple)
        texts = []
        for k, at in enumerate(chosen.tolist()):  # one long text of many pieces, cut where a token opens with a blank
            size += len(pieces[at])
            if size >= BATCH_BYTES or k == len(chosen) - 1:
                texts.append(b"".join([pieces[x] for x in chosen[start : k + 1]]).decode())
                start, size = k + 1, 0
        if texts:
            own = np.concatenate([np.asarray(x, self.kind) for k in range(0, len(texts), 8) for x in self.library.encode(texts[k : k + 8])])
            first = np.flatnonzero(self.library.opens[own])
            if len(first) == len(chosen) and first[0] == 0:
                ends = np.r_[first[1:], len(own)]
                counts[chosen] = ends - first
                for at, a, b in zip(chosen.tolist(), first.tolist(), ends.tolist(), strict=True):
                    parts[at] = own[a:b]
            else:  # a string that the vocabulary adds stands beside a blank: each piece by itself
                simple[:] = False
        rest = np.flatnonzero(~simple).tolist()
        for k in range(0, len(rest), 256):
            block = rest[k : k + 256]
            for at, found in zip(block, self.library.encode([pieces[at].decode() for at in block]), strict=True):
                parts[at], counts[at] = np.asarray(found, self.kind), len(found)
        return np.concatenate([np.zeros(0, self.kind), *parts]) if self.ids else np.zeros(0, self.kind), counts

    def window(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray | None]:
        """(number of ids of each piece, all their ids)."""
        keys = span_hashes(data[starts[0] : ends[-1]], starts - starts[0], ends - starts[0]) | np.uint64(1)
        slot = (keys >> np.uint64(64 - SLOT_BITS)).astype(np.int64)
        counts = self.counts[slot].astype(np.int64)
        at = self.at[slot].astype(np.int64) if self.ids else None
        missed = np.flatnonzero(self.keys[slot] != keys)
        fresh = np.zeros(0, self.kind)
        if len(missed):
            _, first, which = np.unique(keys[missed], return_index=True, return_inverse=True)
            chosen = missed[first]
            raw, base = data[starts[0] : ends[-1]].tobytes(), int(starts[0])
            fresh, found = self.encoded([raw[a - base : b - base] for a, b in zip(starts[chosen].tolist(), ends[chosen].tolist(), strict=True)])
            counts[missed] = found[which]
            begin = np.cumsum(found) - found
            if self.ids:  # new ids are read behind the store
                at[missed] = STORE_IDS + begin[which]
        total = None
        if self.ids:
            place = np.repeat(at - (np.cumsum(counts) - counts), counts) + np.arange(int(counts.sum()))
            new = place >= STORE_IDS
            total = self.store[np.where(new, 0, place)]
            total[new] = fresh[place[new] - STORE_IDS]
        if len(missed):
            keep = np.flatnonzero((ends[chosen] - starts[chosen] <= REMEMBERED_BYTES) & (found > 0))
            if self.ids:
                size = int(found[keep].sum())
                if self.used + size > STORE_IDS:
                    self.forget()
                if size <= STORE_IDS:
                    own = np.cumsum(found[keep]) - found[keep]
                    self.store[self.used : self.used + size] = fresh[np.repeat(begin[keep] - own, found[keep]) + np.arange(size)]
                    self.at[slot[chosen[keep]]] = self.used + own
                    self.used += size
                else:
                    keep = keep[:0]
            self.keys[slot[chosen[keep]]] = keys[chosen[keep]]
            self.counts[slot[chosen[keep]]] = found[keep]
        return counts, total

    def __call__(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray | None]:
        """(number of ids of each text, all their ids or None)."""
        data, offsets = text_buffer(column)
        per, parts = np.zeros(len(offsets) - 1, np.int64), [np.zeros(0, self.kind)]
        if self.library.cuts:  # inside a string that the vocabulary adds, letters and marks belong together
            raw = data.tobytes()
            marks = not any(x in raw for x in self.library.added)
        starts = piece_starts(data, offsets, marks) if self.library.cuts else offsets[:-1][np.diff(offsets) > 0]
        ends = np.r_[starts[1:], len(data)] if len(starts) else starts
        row, first = np.searchsorted(offsets, starts, side="right") - 1, 0
        while first < len(starts):
            stop = max(first + 1, int(np.searchsorted(ends, starts[first] + WINDOW_BYTES, side="right")))
            counts, total = self.window(data, starts[first:stop], ends[first:stop])
            per += np.bincount(row[first:stop], counts, minlength=len(per)).astype(np.int64)
            parts.append(total)
            first = stop
        return per, np.concatenate(parts) if self.ids else None


def encoder(path: str, ids: bool) -> PieceEncoder:
    """One for each worker process, so that later tasks find its pieces."""
    return held_by_worker(("encoder", path, ids), lambda: PieceEncoder(path, ids))


def count_tokens(docs: DataFrame, vocabulary: str = VOCABULARY, limit: int = TOKEN_LIMIT, carried: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit and the `carried` columns of every row of `docs`.

    A null text counts as empty (0 bytes, 0 tokens); a null doc_id stays null; repeated rows each give a row;
    a very long text is counted in windows of WINDOW_BYTES; an empty table gives no row; other columns are not read,
    whatever their names.
    """
    path = vocabulary_path(vocabulary)

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(path, False)
        for batch in batches:
            for part in slices(batch):
                sizes = np.diff(text_buffer(part.column("text"))[1])
                yield pa.record_batch({"doc_id": part.column("doc_id"), "n_bytes": pa.array(sizes, pa.int64()), "n_tokens": pa.array(encode(part.column("text"))[0], pa.int64())} | {c: part.column(c) for c in carried})

    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), *carried)
    schema = T.StructType([T.StructField(c, T.LongType()) for c in ("doc_id", "n_bytes", "n_tokens")] + [rows.schema[c] for c in carried])
    return rows.mapInArrow(tidy(counted), schema).withColumn("over_limit", F.col("n_tokens") > limit)
