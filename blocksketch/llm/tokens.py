"""Token counts by rank-synchronous merging over ragged arrays.

Texts are cut into pre-tokens; the distinct unseen ones of a batch are held
end to end in one array of symbol ids.  In each round every sequence finds the
lowest merge rank among its adjacent pairs and applies that pair everywhere in
the sequence at once; sequences without a known pair leave.  What survives are
the tokens.  Results of distinct pieces are kept in a bounded table per worker,
so common words are merged once.

Defined results: null and empty texts have 0 bytes and 0 tokens; repeated rows
are each reported; other columns are ignored.  Special strings inside a text
are one token each, as the library does by default.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterator
from itertools import compress, repeat
from operator import is_, not_

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from blocksketch.llm.common import row_runs, ship, text_buffer

#: Fixed by the byte-level vocabularies: how text is cut before merging.
PRETOKEN = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+")
#: Where a space meets more white space, cutting at spaces alone would be wrong.
_ODD = re.compile(r" \s|\s ")
_RARE = [c for c in map(chr, range(0x3001)) if c.isspace() and c not in " \n"]
#: Pieces with their space kept per worker, about 200 bytes each, in two generations.
MOST_KEPT = 500_000
#: Bytes of text whose pieces are held as objects at a time.
RUN_BYTES = 1 << 20


def _byte_symbols() -> list[str]:
    """The printable stand-ins of the 256 bytes in byte-level vocabularies."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    out, spare = [""] * 256, 0x100
    for b in range(256):
        if b in plain:
            out[b] = chr(b)
        else:
            out[b] = chr(spare)
            spare += 1
    return out


class Merger:
    """The merge table of a byte-level vocabulary, applied to many sequences at once."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            held = json.load(f)
        vocab, merges = held["model"]["vocab"], held["model"]["merges"]
        merges = [m.split(" ") if isinstance(m, str) else m for m in merges]
        self.specials = [t["content"] for t in held["added_tokens"]]
        self.special_ids = {t["content"]: t["id"] for t in held["added_tokens"]}
        self.special = re.compile("(" + "|".join(re.escape(s) for s in sorted(self.specials, key=len, reverse=True)) + ")") if self.specials else None
        self.first = np.array([vocab[c] for c in _byte_symbols()], np.int64)
        self.size = max(vocab.values()) + 1
        left = np.array([vocab[a] for a, _ in merges], np.int64)
        right = np.array([vocab[b] for _, b in merges], np.int64)
        self.made = np.array([vocab[a + b] for a, b in merges], np.int64)
        self.bits = 20
        self.slots = np.full(1 << self.bits, -1, np.int64)
        self.ranks = np.full(1 << self.bits, len(merges), np.int32)
        self.none = len(merges)
        keys = left * self.size + right
        todo, at = np.arange(len(keys)), self._slot(keys)
        self.probes = 0
        while len(todo):
            self.probes += 1
            free = self.slots[at] == -1
            chosen, first = np.unique(at[free], return_index=True)
            put = np.flatnonzero(free)[first]
            self.slots[chosen], self.ranks[chosen] = keys[todo[put]], todo[put]
            rest = np.ones(len(todo), bool)
            rest[put] = False
            todo, at = todo[rest], (at[rest] + 1) & ((1 << self.bits) - 1)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def rank_of(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        keys = a * self.size + b
        at = self._slot(keys)
        seen = self.slots[at]
        out = np.where(seen == keys, self.ranks[at], self.none)
        open_ = np.flatnonzero((seen != keys) & (seen != -1))
        for _ in range(self.probes):
            if not len(open_):
                break
            at_o = at[open_] = (at[open_] + 1) & ((1 << self.bits) - 1)
            seen_o = self.slots[at_o]
            hit = seen_o == keys[open_]
            out[open_[hit]] = self.ranks[at_o[hit]]
            open_ = open_[~hit & (seen_o != -1)]
        return out

    def merge(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Token ids of all pieces end to end, and the number of each piece's tokens."""
        return self.merge_runs(np.frombuffer(b"".join(pieces), np.uint8), np.fromiter(map(len, pieces), np.int64, len(pieces)))

    def merge_runs(self, data: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The same for pieces that lie end to end."""
        ids = self.first[data]
        owner = np.repeat(np.arange(len(lengths)), lengths)
        done_ids, done_owner = [ids[:0]], [owner[:0]]
        while len(ids):
            pair = owner[1:] == owner[:-1]
            rank = np.full(len(ids), self.none, np.int64)
            at = np.flatnonzero(pair)
            rank[at] = self.rank_of(ids[at], ids[at + 1])
            starts = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
            least = np.minimum.reduceat(rank, starts)
            sizes = np.diff(np.r_[starts, len(ids)])
            active = np.repeat(least < self.none, sizes)
            if not active.all():
                done_ids.append(ids[~active])
                done_owner.append(owner[~active])
            take = active & (rank == np.repeat(least, sizes))
            where = np.flatnonzero(take)
            if len(where):
                # in a run of touching matches (aaa) every second one applies
                new = np.r_[True, np.diff(where) != 1]
                run_start = np.maximum.accumulate(np.where(new, np.arange(len(where)), 0))
                where = where[(np.arange(len(where)) - run_start) % 2 == 0]
                ids = ids.copy()
                ids[where] = self.made[rank[where]]
                keep = active.copy()
                keep[where + 1] = False
            else:
                keep = active
            ids, owner = ids[keep], owner[keep]
        ids, owner = np.concatenate(done_ids), np.concatenate(done_owner)
        order = np.argsort(owner, kind="stable")
        return ids[order], np.bincount(owner, minlength=len(lengths))


def _odd(text: str) -> bool:
    """Whether a space touches more white space."""
    if "  " in text or " \n" in text or "\n " in text:
        return True
    return any(c in text for c in _RARE) and _ODD.search(text) is not None


class PieceTable:
    """Values of pieces: their numbers of tokens, or their ids as little-endian bytes."""

    def __init__(self, path: str, as_ids: bool):
        self.merger, self.as_ids = Merger(path), as_ids
        self.tokens: dict[str, object] = {}
        # two generations: pieces met again move to the young one, the others go when it is full
        self.spaced: dict[str, object] = {}
        self.older: dict[str, object] = {}

    def _values(self, pieces: list[str]) -> list:
        """Of each piece (any text), by its pre-tokens."""
        split = [PRETOKEN.findall(p) for p in pieces]
        new = list({t for s in split for t in s if t not in self.tokens})
        if new:
            ids, counts = self.merger.merge([t.encode() for t in new])
            self.tokens.update(zip(new, self._pieces(ids, counts) if self.as_ids else counts.tolist(), strict=True))
        get = self.tokens.__getitem__
        return [b"".join(map(get, s)) for s in split] if self.as_ids else [sum(map(get, s)) for s in split]

    def _learn(self, new: list[str]) -> None:
        """Adds the values of pieces that follow a space.

        Pure words are one pre-token, and so is the word before a comma or full
        stop; only the rest needs the pre-token pattern.
        """
        new = self._not_older(new)
        pure = list(map(str.isalpha, new))
        words = list(compress(new, pure))
        others = list(compress(new, map(not_, pure)))
        marked = [c for c in others if c[-1:] in (",", ".") and c[:-1].isalpha()]
        rest = set(others).difference(marked)
        self._add_words(words)
        self._add_words(self._not_older(list({c[:-1] for c in marked}.difference(self.spaced))))
        ends_of = dict(zip(",.", self._values([",", "."]), strict=True))
        self.spaced.update([(c, self.spaced[c[:-1]] + ends_of[c[-1]]) for c in marked])
        rest = list(rest)
        self.spaced.update(zip(rest, self._values([" " + c for c in rest]), strict=True))

    def _not_older(self, pieces: list[str]) -> list[str]:
        """The pieces that are in no generation; those of the older one move to the young one."""
        found = list(map(self.older.get, pieces))
        lacks = list(map(is_, found, repeat(None)))
        has = list(map(not_, lacks))
        self.spaced.update(zip(compress(pieces, has), compress(found, has), strict=True))
        return list(compress(pieces, lacks))

    def _add_words(self, words: list[str]) -> None:
        """Pure words with the space before them, merged as they lie end to end."""
        if not words:
            return
        data = np.frombuffer((" " + " ".join(words)).encode(), np.uint8)
        starts = np.flatnonzero(data == 32)
        ids, counts = self.merger.merge_runs(data, np.diff(np.r_[starts, len(data)]))
        self.spaced.update(zip(words, self._pieces(ids, counts) if self.as_ids else counts.tolist(), strict=True))

    @staticmethod
    def _pieces(ids: np.ndarray, counts: np.ndarray) -> Iterator[bytes]:
        raw, ends = ids.astype("<u4").tobytes(), np.cumsum(counts) * 4
        return map(raw.__getitem__, map(slice, (ends - counts * 4).tolist(), ends.tolist()))

    def _whole(self, text: str):
        """A text that can't be cut at spaces, or that holds special strings."""
        parts = self.merger.special.split(text) if self.merger.special else [text]
        ids = self.merger.special_ids
        if self.as_ids:
            return b"".join(ids[p].to_bytes(4, "little") if p in ids else self._values([p])[0] for p in parts if p)
        return sum(1 if p in ids else self._values([p])[0] for p in parts if p)

    def of(self, texts: list[str]) -> list:
        """The value of each text."""
        if len(self.spaced) > MOST_KEPT // 2:
            self.older, self.spaced = self.spaced, {}
        if len(self.tokens) > MOST_KEPT // 4:
            self.tokens.clear()
        specials, known = self.merger.specials, self.spaced.get
        cut, values, missing, heads = [], [], set(), []
        for t in texts:
            if _odd(t) or any(s in t for s in specials):
                cut.append(None)
                values.append(None)
                continue
            head, *pieces = t.split(" ")
            heads.append(head)
            found = list(map(known, pieces))
            lacks = list(map(is_, found, repeat(None)))
            names = list(compress(pieces, lacks))
            missing.update(names)
            cut.append((compress(range(len(found)), lacks), names))
            values.append(found)
        self._learn(list(missing))
        head_values = iter(self._values(heads))
        get, out = self.spaced.__getitem__, []
        for text, holes, found in zip(texts, cut, values, strict=True):
            if found is None:
                out.append(self._whole(text))
                continue
            for i, value in zip(holes[0], map(get, holes[1]), strict=True):
                found[i] = value
            out.append(next(head_values) + (b"".join(found) if self.as_ids else sum(found)))
        return out


_tables: dict[tuple[str, bool], PieceTable] = {}


def piece_table(tokenizer: str, as_ids: bool) -> PieceTable:
    """The worker's own table for a vocabulary, given by name or by path."""
    if (tokenizer, as_ids) not in _tables:
        import public_tokenizers

        path = tokenizer if "/" in tokenizer else str(public_tokenizers.path(tokenizer))
        _tables[tokenizer, as_ids] = PieceTable(path, as_ids)
    return _tables[tokenizer, as_ids]


def runs_of_texts(column: pa.Array) -> Iterator[tuple[int, int, list[str], np.ndarray]]:
    """Runs of rows: start, end, texts (null: empty), bytes of each."""
    _, offsets = text_buffer(column)
    sizes = np.diff(offsets)
    for a, b in row_runs(offsets, RUN_BYTES):
        yield a, b, [t or "" for t in column.slice(a, b - a).to_pylist()], sizes[a:b]


def token_counts(documents: DataFrame, keep: tuple[str, ...] = ("doc_id",), text: str = "text", tokenizer: str = "byte_bpe_50k.json", limit: int = 512) -> DataFrame:
    """``keep`` plus n_bytes, n_tokens and over_limit (n_tokens > limit) of every row.

    ``tokenizer`` is a byte-level BPE file of the tokenizers library: a name
    known to ``public_tokenizers`` or a path on every executor.
    """
    ship(documents.sparkSession)
    src = documents.select(*keep, text)
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in src.schema.fields[:-1]), "n_bytes long", "n_tokens long", "over_limit boolean"])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = piece_table(tokenizer, False)
        for batch in batches:
            tokens, n_bytes = [], []
            for _, _, texts, sizes in runs_of_texts(batch.column(len(keep))):
                tokens += table.of(texts)
                n_bytes.append(sizes)
            n = np.array(tokens, np.int64)
            made = [pa.array(np.concatenate(n_bytes) if n_bytes else n), pa.array(n), pa.array(n > limit)]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], *made], [*keep, "n_bytes", "n_tokens", "over_limit"])

    return src.mapInArrow(count, schema)
