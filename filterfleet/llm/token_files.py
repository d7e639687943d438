"""Token-id files compressed by pair grammars (Re-Pair), with random access.

Documents are encoded, dealt to ranges of ascending doc_id, and cut into blocks of about `block_tokens` ids. In each
block frequent pairs of neighbouring symbols are replaced by new symbols until no pair occurs `least` times. A round
replaces every pair wherever no more frequent pair overlaps it, not one pair of the whole block; counts are exact. A
file row holds a block: its documents' ids and lengths, the rules (left and right symbol of each new one), the expansion
length of each rule, and the remaining sequence. Cumulated expansion lengths say where an id lies, so a stretch of ids
is decoded without the rest (`read_ids`; `read_documents` for given documents).

The container is Parquet in the shared folder: any store Spark can write to will do, and a lost task writes its block
again. Null text counts as empty, so it has the end id alone; null and repeated doc_ids are kept, nulls first,
repeated ones in order of their ids; other columns are ignored; no rows give no blocks and no rows.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from collections.abc import Iterator
from struct import pack

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from filterfleet.llm.byte_bpe import printable_bytes, vocabulary_path
from filterfleet.llm.common import id_buckets, materialize, reduce_tasks, slices, table

END_ID = 1

#: Text of these characters alone needs no normalizer (NFC leaves them as they are, and each has one lower-case form).
SIMPLE = re.compile(r"[\x09-\x0D\x20!-~À-ÖØ-öø-įı-ž]*")
#: The splitting rule of this vocabulary over such characters.
PIECES = re.compile(r"'(?:[stmd]|re|ve|ll)|[a-zß-öø-ž]+|[0-9]|[^\s0-9a-zß-öø-ž]+").findall

#: Byte classes of lowered simple text in UTF-8: white space, letters, digits, other signs, and the two marks below.
WHITE, LETTER, DIGIT, SIGN, MARK = range(5)
CLASS = np.full(256, LETTER, np.uint8)  # two-byte characters that are simple are letters
CLASS[:128] = SIGN
CLASS[[9, 10, 11, 12, 13, 32]], CLASS[48:58], CLASS[97:123] = WHITE, DIGIT, LETTER
#: Marks that no simple text holds: the end of a text, and a word that is not simple.
END_MARK, WORD_MARK = "\x00", "\x01"
CLASS[[ord(END_MARK), ord(WORD_MARK)]] = MARK
#: Where marked text may be cut: no piece goes on before one of these.
CUT = re.compile(rb"[\x00-\x200-9]")
#: The first n of eight bytes.
FIRST_BYTES = np.array([(1 << 8 * n) - 1 for n in range(9)], np.uint64)


def piece_bounds(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(starts, ends) of what PIECES finds in lowered simple text (UTF-8 bytes); each mark is a piece of its own.

    A run of one class is a piece, each digit is one, and an apostrophe that starts a run of signs takes a contraction's letters.
    """
    kind = np.full(len(data) + 4, WHITE, np.uint8)
    kind[1:-3] = CLASS[data]
    start = kind != WHITE
    start[1:] &= (kind[1:] != kind[:-1]) | (kind[1:] == DIGIT) | (kind[1:] == MARK)
    at = np.flatnonzero((data == 39) & start[1:-3])
    if len(at):
        follow = np.concatenate([data, np.zeros(2, np.uint8)])
        x, y = follow[at + 1], follow[at + 2]
        long = ((x == 114) | (x == 118)) & (y == 101) | (x == 108) & (y == 108)  # re, ve, ll
        short = np.isin(x, np.frombuffer(b"stmd", np.uint8))
        at, skip = at[short | long], np.where(long, 3, 2)[short | long]
        start[1 + at + 1] = False
        start[1 + at + skip] |= kind[1 + at + skip] == LETTER
    stop = (kind[:-1] != WHITE) & (start[1:] | (kind[1:] == WHITE))
    return np.flatnonzero(start) - 1, np.flatnonzero(stop)


def distinct(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order that puts equal rows of two numbers side by side; whether each in that order is the first of its kind)."""
    order = np.lexsort((keys[:, 1], keys[:, 0]))
    keys = keys[order]
    return order, np.concatenate([[True], (keys[1:] != keys[:-1]).any(axis=1)])[: len(keys)]


def ranges(begin: np.ndarray, many: np.ndarray) -> np.ndarray:
    """The numbers begin ... begin + many - 1 of all rows, one after the other."""
    return np.arange(int(many.sum())) + np.repeat(begin - (np.cumsum(many) - many), many)


class PieceTable:
    """ids of pieces of up to 16 bytes and 8 ids, looked up for many pieces at once.

    A piece has two places in a table of fixed size; a new one takes its first if that is free, or else its second from
    whatever is there. Rows hold the piece's bytes, so a look-up is exact.
    """

    IDS = 8

    def __init__(self, bits: int):
        """bits: the table has 2 ** bits rows of 40 bytes."""
        self.bits, self.rows = np.uint64(bits), np.zeros((1 << bits, 5), np.uint64)

    def places(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        h = keys[:, 0] * np.uint64(0x9E3779B97F4A7C15) ^ keys[:, 1] * np.uint64(0xC2B2AE3D27D4EB4F)
        h = (h ^ h >> np.uint64(29)) * np.uint64(0xBF58476D1CE4E5B9)
        return (h >> (np.uint64(64) - self.bits)).astype(np.int64), (h >> np.uint64(16) & np.uint64(len(self.rows) - 1)).astype(np.int64)

    def find(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(whether each piece is held, number of its ids, its ids)."""
        one, two = self.places(keys)
        rows = self.rows[one]
        held = (rows[:, :2] == keys).all(axis=1)
        other = np.flatnonzero(~held)
        rows[other] = self.rows[two[other]]
        held[other] = (rows[other, :2] == keys[other]).all(axis=1)
        return held, rows[:, 4].astype(np.int64), np.ascontiguousarray(rows[:, 2:4]).view(np.uint16)

    def put(self, keys: np.ndarray, counts: np.ndarray, ids: np.ndarray) -> None:
        """ids: those of all pieces, one after the other."""
        one, two = self.places(keys)
        rows = np.zeros((len(keys), 5), np.uint64)
        held = np.zeros((len(keys), self.IDS), np.uint16)
        held[np.arange(self.IDS) < counts[:, None]] = ids
        rows[:, :2], rows[:, 2:4], rows[:, 4] = keys, held.view(np.uint64), counts
        self.rows[np.where(self.rows[one, 4] == 0, one, two)] = rows


class PieceMerges:
    """Byte-pair merges of many pieces of up to 16 bytes at once, as the library's model makes them one by one.

    In a round each piece merges its pair of lowest rank, the leftmost of equal ones. The model takes pairs from a queue
    in the same order, as long as no merge stands before those that make its parts (`ordered`).
    """

    NONE = np.int32(2**31 - 1)

    def __init__(self, model: dict, spelled: dict[int, str]):
        """model: the model's part of a tokenizer file; spelled: the character that stands for each byte."""
        vocab, end = model["vocab"], model.get("end_of_word_suffix") or ""
        merges = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        plain = not any(model.get(x) for x in ("dropout", "continuing_subword_prefix", "byte_fallback", "ignore_merges"))
        letters = [c + x for x in ("", end) for c in spelled.values()]
        made_at = {a + b: n for n, (a, b) in enumerate(merges)}
        known = plain and all(x in vocab for x in letters) and all(x in vocab for x in made_at) and len(made_at) == len(merges)
        sound = not any(x in made_at for x in letters) and all(made_at.get(x, -1) < n and x in vocab for n, pair in enumerate(merges) for x in pair)
        self.ordered = known and sound and max(vocab.values()) < 1 << 16
        if not self.ordered:
            return
        self.byte = np.array([[vocab[spelled[b] + x] for b in range(256)] for x in ("", end)], np.int32)
        codes = np.array([vocab[a] << 16 | vocab[b] for a, b in merges], np.uint32)
        order = np.argsort(codes)
        self.codes, self.ranks = np.append(codes[order], np.uint32(2**32 - 1)), np.append(order, self.NONE).astype(np.int32)
        self.made = np.array([vocab[a + b] for a, b in merges], np.int32)

    def rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        code = left.astype(np.uint32) << np.uint32(16) | right.astype(np.uint32)
        at = np.searchsorted(self.codes, code)
        return np.where(self.codes[at] == code, self.ranks[at], self.NONE)

    def __call__(self, keys: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all pieces one after the other, number of ids of each). keys: bytes of each, filled up with noughts to 16."""
        counts, out = lengths.copy(), np.zeros((len(keys), 16), np.int32)
        data, rows = np.ascontiguousarray(keys).view(np.uint8), np.arange(len(keys))
        symbols = self.byte[0][data]
        symbols[rows, lengths - 1] = self.byte[1][data[rows, lengths - 1]]
        pairs = np.flatnonzero(np.arange(1, 16) < lengths[:, None])
        ranks = np.full((len(keys), 15), self.NONE)
        ranks.flat[pairs] = self.rank(symbols[:, :-1].ravel()[pairs], symbols[:, 1:].ravel()[pairs])
        while len(rows):
            best = ranks.argmin(axis=1) if ranks.shape[1] else np.zeros(len(rows), np.int64)
            rank = ranks[np.arange(len(rows)), best] if ranks.shape[1] else np.full(len(rows), self.NONE)
            done = rank == self.NONE
            out[rows[done], : symbols.shape[1]] = symbols[done]
            rows, symbols, ranks, best, rank = rows[~done], symbols[~done], ranks[~done], best[~done], rank[~done]
            if not len(rows):
                break
            counts[rows] -= 1
            before, here = np.arange(symbols.shape[1] - 1) <= best[:, None], np.arange(len(rows))
            symbols = np.where(before, symbols[:, :-1], symbols[:, 1:])
            symbols[here, best] = self.made[rank]
            ranks = np.where(before[:, :-1], ranks[:, :-1], ranks[:, 1:])
            left, right = np.flatnonzero(best > 0), np.flatnonzero(best < counts[rows] - 1)
            last = np.flatnonzero((best == counts[rows] - 1) & (best < ranks.shape[1]))
            ranks[last, best[last]] = self.NONE
            ranks[right, best[right]] = self.rank(symbols[right, best[right]], symbols[right, best[right] + 1])
            ranks[left, best[left] - 1] = self.rank(symbols[left, best[left] - 1], symbols[left, best[left]])
        return out[np.arange(16) < counts[:, None]].astype(np.uint32), counts


class PieceEncoder(dict):
    """ids of whole texts by the tokenizers library, asked only for what this memo of pieces does not hold.

    This vocabulary drops white space, and neither its normalizer nor its splitting rule looks across blanks, tabs and
    line ends; so a text's ids are its words' ids one after the other. Text of simple characters is lowered, and split
    into pieces here for many texts at once. Pieces of up to 16 bytes are held in a `PieceTable`; new ones go through
    `PieceMerges`, and through the library's model if that does not hold for a vocabulary, as longer pieces do. Any
    other word goes through the whole library.

    The memo of what the library was asked for has two generations: what was asked for lately is kept when the older one
    is dropped.
    """

    MOST = 2 << 20  # bytes that are split at a time, or to the next place for a cut

    def __init__(self, path: str, most: int = 200_000, bits: int = 20):
        """most: bound of the memo, about 150 bytes an entry; bits: size of the table, 40 MB by default."""
        super().__init__()
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.tokenize = self.library.model.tokenize
        self.special = [t.content for t in self.library.get_added_tokens_decoder().values()]
        self.spelled = {byte: character for character, byte in printable_bytes().items()}
        self.half, self.older = most // 2, {}
        self.narrow = max(self.library.get_vocab().values()) < 1 << 16  # what the table can hold
        self.table, self.merges = PieceTable(bits), PieceMerges(json.loads(self.library.to_str())["model"], self.spelled)

    def __missing__(self, piece: str) -> bytes:
        value = self.older.get(piece)
        if value is None:
            if piece[0] == " ":
                ids = self.library.encode(piece[1:], add_special_tokens=False).ids
            else:
                ids = [t.id for t in self.tokenize(piece if piece.isascii() else piece.encode().decode("latin-1").translate(self.spelled))]
            value = pack(f"<{len(ids)}I", *ids)
        if len(self) >= self.half:
            self.older = dict(self)
            self.clear()
        self[piece] = value
        return value

    def _is_simple(self, text: str) -> bool:
        return SIMPLE.fullmatch(text) is not None and not any(s in text for s in self.special)

    def _marked(self, text: str, others: list[str]) -> str:
        """The text, lowered; words that are not simple go to `others`, with a blank before them, and a mark stands for each."""
        if self._is_simple(text):
            return text.lower()
        words = []
        for w in text.encode().split():
            w = w.decode()
            if self._is_simple(w):
                words.append(w.lower())
            else:
                words.append(WORD_MARK)
                others.append(" " + w)
        return " ".join(words)

    def encode_texts(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts one after the other, each with the end id, as unsigned 32-bit; number of ids of each text)."""
        others: list[str] = []
        raw = "".join([self._marked(x or "", others) + END_MARK for x in texts]).encode()
        found, ends, at, total, other = [np.empty(0, np.uint32)], [np.empty(0, np.int64)], 0, 0, iter(others)
        while at < len(raw):
            cut = CUT.search(raw, at + self.MOST)
            stop = cut.start() if cut else len(raw)
            ids, stops = self._encode(raw[at:stop], other)
            found.append(ids)
            ends.append(total + stops)
            at, total = stop, total + len(ids)
        return np.concatenate(found), np.diff(np.concatenate(ends), prepend=0)

    def _encode(self, raw: bytes, others: Iterator[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of marked text in UTF-8; where among them texts end)."""
        padded = np.frombuffer(raw + bytes(16), np.uint8)
        data = padded[: len(raw)]
        starts, ends = piece_bounds(data)
        lengths, first = ends - starts, data[starts]
        end, word = first == ord(END_MARK), first == ord(WORD_MARK)
        eight = np.ndarray(len(raw) + 9, "<u8", padded, 0, (1,))  # the eight bytes from each place on
        keys = np.empty((len(starts), 2), np.uint64)
        keys[:, 0] = eight[starts] & FIRST_BYTES[np.minimum(lengths, 8)]
        keys[:, 1] = eight[starts + 8] & FIRST_BYTES[np.clip(lengths - 8, 0, 8)]
        fits = (lengths <= 16) & ~end & ~word
        held, counts, ids = self.table.find(keys)
        held &= fits
        counts[end], ids[end, 0] = 1, END_ID
        known = held | end
        fresh = fits & ~held & self.merges.ordered
        parts = []
        if len(at := np.flatnonzero(fresh)):
            order, first = distinct(keys[at])
            new = at[order[first]]
            merged, many = self.merges(keys[new], lengths[new])
            which = np.empty(len(at), np.int64)
            which[order] = np.cumsum(first) - 1
            counts[at] = many[which]
            parts.append((at, merged[ranges((np.cumsum(many) - many)[which], many[which])]))
        if len(at := np.flatnonzero(~known & ~fresh)):
            values = [self[next(others) if w else raw[a:b].decode()] for a, b, w in zip(starts[at].tolist(), ends[at].tolist(), word[at].tolist())]
            counts[at] = np.fromiter(map(len, values), np.int64, len(values)) // 4
            parts.append((at, np.frombuffer(b"".join(values), "<u4")))
        stops = np.cumsum(counts)
        out = np.empty(int(counts.sum()), np.uint32)
        out[np.repeat(known, counts)] = ids[known][np.arange(PieceTable.IDS) < counts[known][:, None]]
        for at, new in parts:
            out[ranges(stops[at] - counts[at], counts[at])] = new
            keep = fits[at] & (counts[at] <= PieceTable.IDS) & self.narrow
            self.table.put(keys[at[keep]], counts[at[keep]], new[np.repeat(keep, counts[at])])
        return out, stops[end]

    def encode_batch(self, texts: list[str | None]) -> list[bytes]:
        """ids of each text with the end id, little-endian unsigned 32-bit."""
        ids, counts = self.encode_texts(texts)
        raw, stops = ids.astype("<u4").tobytes(), np.cumsum(4 * counts).tolist()
        return [raw[a:b] for a, b in zip([0, *stops], stops)]


_encoders: dict[str, PieceEncoder] = {}


def encoded(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, ids (binary, little-endian unsigned 32-bit, with the end id)."""

    def run(batches):
        if path not in _encoders:
            _encoders[path] = PieceEncoder(path)
        for batch in batches:
            for part in slices(batch, "text"):
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(_encoders[path].encode_batch(part.column("text").to_pylist()), pa.binary())], names=["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("bigint"), "text").mapInArrow(run, "doc_id bigint, ids binary")


def pair_ranks(seq: np.ndarray, least: int, places: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(distinct pairs that occur `least` times or more as rows, rarest first; for each place 1 + the number of its pair, or 0).

    places: where pairs are counted, ascending; everywhere by default.
    """
    places = np.arange(len(seq) - 1) if places is None else places
    wide, far = int(seq.max()).bit_length(), len(seq).bit_length()
    code = seq[places].astype(np.int64) << wide | seq[places + 1]
    if 2 * wide + far <= 63:
        order = np.sort(code << far | places)
        code, order = order >> far, order & ((1 << far) - 1)
    else:
        order = np.argsort(code, kind="stable")
        code, order = code[order], places[order]
    start = np.flatnonzero(np.concatenate([[True], code[1:] != code[:-1]])) if len(code) else np.empty(0, np.int64)
    counts = np.diff(start, append=len(code))
    often = np.flatnonzero(counts >= least)
    often = often[np.argsort(counts[often], kind="stable")]
    of_run = np.zeros(len(start), np.int32)
    of_run[often] = np.arange(1, len(often) + 1)
    ranks = np.zeros(len(seq) + 1, np.int32)  # a nought before the first pair and after the last
    ranks[order + 1] = np.repeat(of_run, counts)
    pairs = code[start[often]]
    return np.column_stack([pairs >> wide, pairs & ((1 << wide) - 1)]), ranks


def replace_pairs(ids: np.ndarray, first: int, least: int = 8) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(sequence, rules, lengths): symbols from `first` on, which is above all ids, stand for their rule's two symbols.

    A place is replaced if no pair that overlaps it is more frequent; of a pair that overlaps itself the left one goes.
    The most frequent pair wins everywhere, so each round makes progress, and the rounds end when no pair occurs `least`
    times. A pair without a symbol of the last round can only have become rarer, so after the first round only pairs
    with such a symbol, and those that were frequent before, are counted.
    """
    seq, rules, lengths, places = ids.astype(np.int32), [np.empty((0, 2), np.int64)], np.ones(first, np.int64), None
    while len(seq) > least:
        pairs, ranks = pair_ranks(seq, least, places)
        here = ranks[1:-1]
        at = np.flatnonzero((here > 0) & (here >= ranks[:-2]) & (here >= ranks[2:]))
        if not len(at):
            break
        fresh = np.concatenate([[True], np.diff(at) > 1])
        head = np.maximum.accumulate(np.where(fresh, np.arange(len(at)), 0))
        at = at[(np.arange(len(at)) - head) % 2 == 0]
        uses = np.bincount(here[at], minlength=len(pairs) + 1)
        used = np.flatnonzero(uses >= max(2, least // 2))
        number = np.zeros(len(uses), np.int64)
        number[used] = np.arange(len(lengths), len(lengths) + len(used))
        symbol = number[here[at]]
        at, symbol = at[symbol > 0], symbol[symbol > 0]
        rules.append(pairs[used - 1])
        lengths = np.concatenate([lengths, lengths[rules[-1]].sum(axis=1)])
        open_, keep = np.append(here > 0, False), np.ones(len(seq), bool)
        open_[at], open_[at[at > 0] - 1] = True, True
        seq[at], keep[at + 1] = symbol, False
        seq = seq[keep]
        places = np.flatnonzero(open_[keep][:-1])
    return seq.astype(np.uint32), np.concatenate(rules).astype(np.uint32), lengths[first:].astype(np.uint32)


def expanded(seq: np.ndarray, rules: np.ndarray, first: int) -> np.ndarray:
    """The ids that symbols stand for; each step puts a rule's two symbols in place of every symbol that has a rule."""
    while (new := seq >= first).any():
        at = np.flatnonzero(new)
        rule = seq[at] - first
        at = at + np.arange(len(at))
        seq = np.repeat(seq, 1 + new)
        seq[at], seq[at + 1] = rules[rule].T
    return seq


def read_ids(seq: np.ndarray, rules: np.ndarray, lengths: np.ndarray, first: int, start: int = 0, stop: int | None = None) -> np.ndarray:
    """ids start ... stop of a block; only the rules of symbols that cover them are expanded, each once."""
    size = np.ones(len(seq), np.int64)
    new = np.flatnonzero(seq >= first)
    size[new] = lengths[seq[new] - first]
    ends = np.cumsum(size)
    stop = int(size.sum()) if stop is None else stop
    if stop <= start:
        return np.empty(0, np.uint32)
    a, b = np.searchsorted(ends, start, "right"), np.searchsorted(ends, stop, "left") + 1
    part, size, skip = seq[a:b].astype(np.int64), size[a:b], start - int(ends[a] - size[a])
    needed = np.zeros(len(rules), bool)
    needed[part[part >= first] - first] = True
    used = np.flatnonzero(needed)
    flat = expanded((used + first).astype(seq.dtype), rules, first)
    offset = np.zeros(len(rules), np.int64)
    offset[used] = np.cumsum(lengths[used], dtype=np.int64) - lengths[used]
    begin = np.cumsum(size) - size  # of each symbol in the output
    out, many = np.repeat(part, size), np.repeat(part >= first, size)
    from_rule = np.where(part >= first, offset[np.maximum(part - first, 0)], 0) - begin if len(rules) else -begin
    at = np.flatnonzero(many)
    out[at] = flat[np.repeat(from_rule, size)[at] + at]
    return out[skip : skip + stop - start].astype(np.uint32)


BLOCK = "bucket int, block int, first_symbol bigint, n_tokens bigint, n_docs bigint, doc_ids array<bigint>, doc_lengths binary, rules binary, rule_lengths binary, sequence binary"


def write_files(docs: DataFrame, path: str, first: int = 1 << 16, block_tokens: int = 1 << 18) -> DataFrame:
    """Encodes docs and writes the blocks in ascending order of doc_id; returns the table of blocks as written."""
    tasks = reduce_tasks(docs.sparkSession)
    bucket = id_buckets(docs, tasks)
    names = [x.split()[0] for x in BLOCK.split(", ")]

    def run(batches):
        at, block, held, held_ids, held_tokens = None, 0, [], [], 0

        def close():
            ids = np.frombuffer(b"".join(held), "<u4")
            seq, rules, lengths = replace_pairs(ids, first)
            fields = [at, block, first, len(ids), len(held), held_ids, np.asarray([len(x) // 4 for x in held], "<i8").tobytes(), rules.astype("<u4").tobytes(), lengths.astype("<u4").tobytes(), seq.astype("<u4").tobytes()]
            kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), *[pa.binary()] * 4]
            return pa.RecordBatch.from_arrays([pa.array([x], k) for x, k in zip(fields, kinds)], names=names)

        for batch in batches:
            for b, doc_id, ids in zip(batch.column("bucket").to_pylist(), batch.column("doc_id").to_pylist(), batch.column("ids")):
                if held and (b != at or held_tokens >= block_tokens):
                    yield close()
                    block = block + 1 if b == at else 0
                    held, held_ids, held_tokens = [], [], 0
                at = b
                held.append(ids.as_py())
                held_ids.append(doc_id)
                held_tokens += len(held[-1]) // 4
        if held:
            yield close()

    rows = encoded(docs, path).withColumn("bucket", bucket)
    ordered = rows.repartitionById(tasks, F.col("bucket")).sortWithinPartitions("bucket", F.col("doc_id").asc_nulls_first(), "ids")
    return materialize(ordered.mapInArrow(run, BLOCK), "token-files")


DOCS = "bucket int, block int, doc_id bigint, within bigint, n_tokens bigint, ids_crc32 bigint"


def read_files(files: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files."""

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                of = lambda c, kind="<u4": np.frombuffer(row[c], kind)  # noqa: E731, B023
                ids = read_ids(of("sequence"), of("rules").reshape(-1, 2), of("rule_lengths"), row["first_symbol"]).astype("<u4")
                lengths, keys = of("doc_lengths", "<i8"), row["doc_ids"]
                starts = np.cumsum(lengths) - lengths
                sums = [zlib.crc32(ids[a : a + n].tobytes()) for a, n in zip(starts.tolist(), lengths.tolist())]
                n = len(keys)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([row["bucket"]] * n, pa.int32()), pa.array([row["block"]] * n, pa.int32()), pa.array(keys, pa.int64()), pa.array(starts, pa.int64()), pa.array(lengths, pa.int64()), pa.array(sums, pa.int64())],
                    names=[x.split()[0] for x in DOCS.split(", ")],
                )

    blocks = files.select("bucket", "block", "n_tokens")
    earlier = Window.partitionBy(F.lit(0)).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    totals = blocks.groupBy("bucket").agg(F.sum("n_tokens").alias("all")).withColumn("before_bucket", F.coalesce(F.sum("all").over(earlier), F.lit(0)))  # a row for each bucket
    inside = Window.partitionBy("bucket").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    starts = blocks.withColumn("before_block", F.coalesce(F.sum("n_tokens").over(inside), F.lit(0))).join(totals, "bucket").selectExpr("bucket", "block", "before_bucket + before_block as before")
    return files.drop("n_tokens").mapInArrow(run, DOCS).join(starts, ["bucket", "block"]).selectExpr("doc_id", "before + within as start", "n_tokens", "ids_crc32")


def read_documents(files: DataFrame, asked: DataFrame) -> DataFrame:
    """doc_id, ids (binary, little-endian unsigned 32-bit, with the end id) of the documents with an id in asked (doc_id).

    Only blocks that hold one are read, and of these only the stretches asked for are decoded.
    """
    held = files.select("bucket", "block", F.explode("doc_ids").alias("doc_id")).join(asked.select("doc_id").distinct(), "doc_id", "left_semi")
    wanted = held.groupBy("bucket", "block").agg(F.collect_set("doc_id").alias("wanted"))

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                of = lambda c, kind="<u4": np.frombuffer(row[c], kind)  # noqa: E731, B023
                wanted, ends = set(row["wanted"]), np.cumsum(of("doc_lengths", "<i8"))
                found = []
                for doc_id, a, b in zip(row["doc_ids"], [0, *ends[:-1].tolist()], ends.tolist()):
                    if doc_id in wanted:
                        found.append((doc_id, read_ids(of("sequence"), of("rules").reshape(-1, 2), of("rule_lengths"), row["first_symbol"], a, b).astype("<u4").tobytes()))
                yield pa.RecordBatch.from_arrays([pa.array([d for d, _ in found], pa.int64()), pa.array([x for _, x in found], pa.binary())], names=["doc_id", "ids"])

    return files.join(wanted, ["bucket", "block"]).mapInArrow(run, "doc_id bigint, ids binary")


def op10_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_files(write_files(table(spark, sf_dir, "documents"), vocabulary_path("word_bpe_49k.json")))


QUERIES = {"op10_token_files": op10_token_files}
ORACLES: dict = {}
