"""Byte-level BPE encoding and decoding by dynamic programming over prefixes.

A piece of text (as the vocabulary's own splitting rule cuts it) is encoded from left to right: for every prefix there
is exactly one token that can be the last one of its BPE encoding. An automaton over the vocabulary names the tokens
that end at each position; a token is the right one if the prefix before it has an encoding whose own last token is
compatible with it, which means that BPE applied to the two tokens' bytes would leave exactly these two tokens. The
stored last tokens are then followed back from the end. Work is linear in the piece (times the longest token), however
long the piece is; pieces seen before are answered from a bounded memo, and so are pairs.

Null text counts as empty and has no ids. Strings of special tokens inside a text become the special ids, as the
tokenizers library does by default. Repeated rows are encoded each; other columns pass through `encode` and `decode`
(a clashing `ids` or `decoded` is replaced); no rows give no rows.
"""

from __future__ import annotations

import hashlib
import json

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, types as T

from filterfleet.llm.common import released, slices, table

#: The splitting rule of this vocabulary.
SPLIT_RULE = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
NEVER = 1 << 40


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def printable_bytes() -> dict[str, int]:
    """The vocabulary file spells each byte as one printable character: itself where it is printable, else the next free one from 256."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return {chr(b) if b in plain else chr(next(rest)): b for b in range(256)}


class PrefixBpe:
    """Encoder and decoder of one vocabulary file."""

    def __init__(self, path: str, most_pieces: int = 100_000, most_pairs: int = 100_000):
        """most_pieces, most_pairs: bounds of the memos, about 150 bytes each."""
        import ahocorasick
        import regex

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        byte_of = printable_bytes()
        ids: dict[str, int] = spec["model"]["vocab"]
        self.bytes_of = {i: bytes(byte_of[c] for c in s) for s, i in ids.items()}
        self.special = {x["content"]: x["id"] for x in spec["added_tokens"]}
        self.bytes_of.update({i: s.encode() for s, i in self.special.items()})
        self.split = regex.compile(SPLIT_RULE).findall
        self.cut = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")").split if self.special else None
        self.rank: dict[tuple[int, int], int] = {}
        halves: dict[int, tuple[int, int]] = {}
        for rank, (a, b) in enumerate(spec["model"]["merges"]):
            pair = ids[a], ids[b]
            self.rank[pair] = rank
            halves.setdefault(ids[a + b], pair)
        self.automaton = ahocorasick.Automaton()
        self.halves = halves
        self.edges: tuple[dict, dict] = ({}, {})  # left and right ends of tokens, as they are asked for
        for token in ids.values():
            text = self.bytes_of[token].decode("latin-1")
            self.automaton.add_word(text, (token, len(text)))
        self.automaton.make_automaton()
        self.most_pieces, self.most_pairs = most_pieces, most_pairs
        self.pieces: dict[str, bytes] = {}
        self.pairs: dict[tuple[int, int], bool] = {}

    def _edge(self, token: int, side: int) -> list[tuple[int, int]]:
        """The parts of a token that lie at one end, innermost first, each with the rank of the merge that absorbs it."""
        known = self.edges[side].get(token)
        if known is None:
            known, above, part = [], NEVER, token
            while True:
                known.append((part, above))
                if part not in self.halves:
                    break
                pair = self.halves[part]
                above, part = self.rank[pair], pair[side]
            self.edges[side][token] = known = known[::-1]
        return known

    def compatible(self, a: int, b: int) -> bool:
        """Whether BPE on the bytes of a and b together ends with a, b: no merge across the seam ever comes first."""
        known = self.pairs.get((a, b))
        if known is not None:
            return known
        left, right, i, j, fine = self._edge(a, 1), self._edge(b, 0), 0, 0, True
        while True:
            (x, x_goes), (y, y_goes) = left[i], right[j]
            seam = self.rank.get((x, y), NEVER)
            if seam < x_goes and seam <= y_goes and seam < NEVER:  # of equal merges the leftmost comes first
                fine = False
                break
            if x_goes == y_goes == NEVER:
                break
            if x_goes <= y_goes:
                i += 1
            else:
                j += 1
        if len(self.pairs) >= self.most_pairs:
            self.pairs.clear()
        self.pairs[a, b] = fine
        return fine

    def encode_piece(self, piece: bytes) -> list[int]:
        last, size = [-1] * (len(piece) + 1), [0] * (len(piece) + 1)
        compatible = self.compatible
        for at, (token, n) in self.automaton.iter(piece.decode("latin-1")):  # longest match of an end first
            end = at + 1
            if last[end] < 0:
                before = end - n
                if before == 0 or (last[before] >= 0 and compatible(last[before], token)):
                    last[end], size[end] = token, n
        out, end = [], len(piece)
        while end:
            out.append(last[end])
            end -= size[end]
        return out[::-1]

    def _packed(self, piece: str) -> bytes:
        if len(self.pieces) >= self.most_pieces:
            self.pieces.clear()
        packed = np.asarray(self.encode_piece(piece.encode()), "<u4").tobytes()
        if len(piece) <= 64:
            self.pieces[piece] = packed
        return packed

    def encode(self, text: str | None) -> np.ndarray:
        """ids of a whole text, little-endian unsigned 32-bit."""
        if not text:
            return np.empty(0, "<u4")
        parts = self.cut(text) if self.cut and any(s in text for s in self.special) else [text]
        known, out = self.pieces.get, []
        for k, part in enumerate(parts):
            if k % 2:
                out.append(np.asarray([self.special[part]], "<u4").tobytes())
            else:
                out += [known(p) or self._packed(p) for p in self.split(part)]
        return np.frombuffer(b"".join(out), "<u4")

    def decode(self, ids) -> str:
        return b"".join(map(self.bytes_of.__getitem__, np.asarray(ids).tolist())).decode("utf-8", "replace")


_loaded: dict[str, PrefixBpe] = {}


def loaded(path: str, memo: int = 100_000) -> PrefixBpe:
    """One encoder for each Python worker and vocabulary; its memos grow to the largest size asked for."""
    if path not in _loaded:
        _loaded[path] = PrefixBpe(path)
    bpe = _loaded[path]
    bpe.most_pieces, bpe.most_pairs = max(bpe.most_pieces, memo), max(bpe.most_pairs, memo)
    return bpe


def _with(schema: T.StructType, name: str, kind: T.DataType) -> T.StructType:
    return T.StructType([f for f in schema.fields if f.name.lower() != name] + [T.StructField(name, kind)])


def _extended(batch: pa.RecordBatch, schema: T.StructType, column: pa.Array) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([*(batch.column(f.name) for f in schema.fields[:-1]), column], names=schema.fieldNames())


def encode(docs: DataFrame, path: str, text: str = "text") -> DataFrame:
    """docs with a column ids (array of int)."""
    schema = _with(docs.schema, "ids", T.ArrayType(T.IntegerType()))

    def run(batches):
        bpe = loaded(path)
        for batch in batches:
            for part in slices(batch, text):
                ids = [bpe.encode(x) for x in part.column(text).to_pylist()]
                ends = np.cumsum([0, *map(len, ids)]).astype(np.int32)
                yield _extended(part, schema, pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(ids).astype(np.int32) if ids else np.empty(0, np.int32))))

    return docs.mapInArrow(released(run), schema)


def decode(tokens: DataFrame, path: str) -> DataFrame:
    """tokens with a column decoded (string)."""
    schema = _with(tokens.schema, "decoded", T.StringType())

    def run(batches):
        bpe = loaded(path)
        for batch in batches:
            for start in range(0, batch.num_rows, 500):
                part = batch.slice(start, 500)
                yield _extended(part, schema, pa.array([bpe.decode(x or []) for x in part.column("ids").to_pylist()], pa.string()))

    return tokens.mapInArrow(released(run), schema)


def digests(docs: DataFrame, path: str, keep: tuple[str, ...] = ("doc_id",), memo: int = 400_000) -> DataFrame:
    """Encodes and decodes every text in one pass; returns n_tokens and the digests of ids and decoded text."""
    schema = T.StructType([*(docs.schema[c] for c in keep), T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())])

    def run(batches):
        bpe = loaded(path, memo)
        for batch in batches:
            counts, ids_sha, text_sha = [], [], []
            for text in batch.column("text"):
                ids = bpe.encode(text.as_py())
                counts.append(len(ids))
                ids_sha.append(hashlib.sha256(ids.tobytes()).hexdigest())
                text_sha.append(hashlib.sha256(bpe.decode(ids).encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(counts, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())], names=schema.fieldNames())

    return docs.select(*keep, "text").mapInArrow(released(run), schema)


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(table(spark, sf_dir, "documents"), vocabulary_path("byte_bpe_50k.json"))


QUERIES = {"op2_byte_bpe": op2_byte_bpe}
ORACLES: dict = {}
