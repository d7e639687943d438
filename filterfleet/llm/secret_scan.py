"""Secret scans: three fixed patterns, and strings that stay incompressible beside their own surroundings.

The fixed patterns always report. A further candidate is a run of 16 or more credential characters near a word of
sensitive context (it starts within `reach` characters after the word, or ends within as many before it) that no fixed
pattern reports as a whole. Its novelty is the marginal cost in zstandard: the compressed size of the surrounding text
with the candidate, less that without it, both primed with a dictionary, divided by the candidate's length. The
dictionary holds common words and the most frequent parts of identifiers in the whole corpus (`identifier_primer`).
Words, paths and repeated identifiers cost little; random keys cost nearly their own length, whatever classes of
characters they mix; so does a long word or path that neither the dictionary nor the surroundings hold. Novel
candidates are reported as `novel`, from end to end.

A run wrapped into lines of one width (and a shorter last one) is one candidate. Such a block, and a run of more than 512
characters, is judged in pieces of 64 beside what stands around all of it, and is reported whole if a piece is novel.
Other runs in the surroundings count only if they have eight characters in a row in common with the candidate.
After a candidate that is reported, runs with only white space between are candidates too, however far they reach. A
last line of under 16 characters belongs to a block of two equal lines or more, or one that a closing line follows.

Null text counts as empty and has no spans. Offsets are code points, ends exclusive. Repeated rows are scanned each;
columns other than doc_id and text are ignored; no rows give no rows.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_right
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from filterfleet.llm.common import materialize, released, slices, table

KINDS = ("assign", "access", "hex", "novel")
#: The base patterns and their least lengths.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
HEX = re.compile(r"[0-9a-f]{16,}")
LEAST_ASSIGN = 12
#: Words of sensitive context.
CONTEXT = re.compile(r"(?:password|passwd|pwd|secret|token|api[_ -]?key|credential|private[_ -]?key|auth|bearer|access[_ -]?key|signature|cookie|session)", re.I | re.A)
LEAST = 16
CANDIDATE = re.compile(r"(?:(?<!\\)|(?![nrt]))[A-Za-z0-9+/_=~.-]{16,}")  # not from the letter of an escape on
#: White space, also as escapes in strings; a run alone on the next line; the line that closes a key.
GAP = re.compile(r"(?:\s|\\[nrt])+")
LINE = re.compile(r"(?:[\x20\t\r]*\n|(?:\\r)?\\n)[\x20\t]*([A-Za-z0-9+/_=~.-]+)(?=[\x20\t\r]*(?:\n|\Z)|\\[nr])", re.A)
CLOSING = re.compile(r"(?:\s|\\[nrt])*-----END", re.A)
#: Identifiers and words that code and prose around secrets are made of.
PRIMER = (
    "password passwd secret token api_key apikey credential private_key access_key authorization bearer session cookie signature username client_id client_secret "
    "function return import export default const class public static void string config settings environment localhost example.com http https www index.html "
    "abcdefghijklmnopqrstuvwxyz ABCDEFGHIJKLMNOPQRSTUVWXYZ 0123456789 test user admin root value name key data file path version license apache copyright "
    "the and that with this from which their there would about other than into could been have were"
)


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the fixed patterns' matches, by start and then kind as listed."""
    spans = [(*m.span(), 0) for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST_ASSIGN]
    spans += [(*m.span(), 1) for m in ACCESS.finditer(text)] if "AKIA" in text else []
    spans += [(*m.span(), 2) for m in HEX.finditer(text)]
    return [(a, b, KINDS[k]) for a, b, k in sorted(spans, key=lambda x: (x[0], x[2]))]


#: A part of an identifier: one word of 3 to 12 letters, as cases, digits and signs divide it. Longer runs of letters are
#: left out, so that a key that many copies of a text hold does not become a word of the dictionary.
PART = re.compile(r"(?:[A-Z][a-z]{2,11}|(?<![A-Za-z])[a-z]{3,12})(?![a-z])")


def identifier_primer(docs: DataFrame, most: int = 4000) -> str:
    """PRIMER and the corpus's `most` most frequent parts of identifiers, the most frequent ones last (nearest to the text).

    All texts are counted; batches are counted before the shuffle, and `most` words come to the driver.
    """

    def count(batches):
        held: Counter = Counter()
        rows = lambda: pa.RecordBatch.from_arrays([pa.array(list(held), pa.string()), pa.array(list(held.values()), pa.int64())], names=["part", "n"])
        for batch in batches:
            for piece in slices(batch, "text"):
                for text in piece.column("text").to_pylist():
                    held.update(PART.findall(text or ""))
                if len(held) > 100_000:
                    yield rows()
                    held.clear()
        if held:
            yield rows()

    counted = docs.select("text").mapInArrow(released(count), "part string, n bigint").groupBy("part").agg(F.sum("n").alias("n"))
    top = materialize(counted.orderBy(F.desc("n"), "part").limit(most), "identifier-parts").collect()  # tasks merge their tops, not the driver
    top.sort(key=lambda r: (-r["n"], r["part"]))
    return " ".join([*(r["part"] for r in reversed(top)), PRIMER])


class Novelty:
    """Marginal compressed bytes a character, primed with a dictionary."""

    def __init__(self, primer: str = PRIMER, level: int = 3):
        import zstandard

        primed = zstandard.ZstdCompressionDict(primer.encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        primed.precompute_compress(level=level)
        compress = zstandard.ZstdCompressor(dict_data=primed, write_content_size=False).compress
        self.size = lambda data: len(compress(data))

    def rate(self, before: str, candidate: str, after: str) -> float:
        around = (before + "\n" + after).encode()
        return (self.size(around + b"\n" + candidate.encode()) - self.size(around + b"\n")) / len(candidate)


_novelty: dict[str, Novelty] = {}


def novelty_of(primer: str) -> Novelty:
    """One of each primer for each Python worker."""
    if primer not in _novelty:
        _novelty.clear()
        _novelty[primer] = Novelty(primer)
    return _novelty[primer]


def block_lines(text: str, start: int, end: int) -> list[tuple[int, int]]:
    """The run and the lines below that wrap it: of its width, each alone on its line, and at last a shorter one."""
    lines = [(start, end)]
    while m := LINE.match(text, lines[-1][1]):
        wide, before = m.end(1) - m.start(1), lines[-1][1] - lines[-1][0]
        if wide > before or m[1].startswith("-----"):
            break
        if wide < before:
            if len(lines) > 1 or CLOSING.match(text, m.end()):
                lines.append(m.span(1))
            break
        lines.append(m.span(1))
    return lines


def without_others(window: str, s: str, shared: int = 8) -> str:
    """The window less runs that have nothing in common with s: other keys would make the letters of s look usual."""
    return CANDIDATE.sub(lambda m: m[0] if any(m[0][k : k + shared] in s for k in range(len(m[0]) - shared + 1)) else "", window)


def lines_above(runs: list[tuple[int, int]], k: int, text: str) -> list[tuple[int, int]]:
    """Run k and the runs above that it is wrapped with: all of one width, each alone on its line but the first."""
    lines = [runs[k]]
    while k and (gap := GAP.fullmatch(text, runs[k - 1][1], lines[0][0])):
        wide = runs[k - 1][1] - runs[k - 1][0]
        if not ("\n" in gap[0] or "\\n" in gap[0]) or wide < lines[0][1] - lines[0][0] or len(lines) > 1 and wide != lines[0][1] - lines[0][0]:
            break
        k -= 1
        lines.insert(0, runs[k])
    return lines


def novel_spans(
    text: str, base: list[tuple[int, int, str]], novelty: Novelty | None = None, least_rate: float = 0.6, reach: int = 48, around: int = 400, whole: int = 512, piece: int = 64
) -> list[tuple[int, int, str]]:
    """Candidates in sensitive context that the dictionary and the surroundings don't explain, and novel runs that follow them."""
    near = [m.span() for m in CONTEXT.finditer(text)]
    if not near:
        return []
    rate = (novelty or novelty_of(PRIMER)).rate
    found, taken, dull = [], 0, 0
    known = lambda s, e: any(a <= s and e <= b for a, b, _ in base)

    def novel(lines: list[tuple[int, int]], most: int | None = None) -> bool:
        s = "".join(text[a:b] for a, b in lines)[:most]
        step = len(s) if len(lines) == 1 and len(s) <= whole and most is None else piece
        before, after = (without_others(w, s) for w in (text[max(0, lines[0][0] - around) : lines[0][0]], text[lines[-1][1] : lines[-1][1] + around]))
        return any(rate(before, s[k : k + step], after) >= least_rate for k in range(0, max(1, len(s) - step // 2), step))

    for _, at in near:
        start = max(at, taken)
        while m := CANDIDATE.search(text, start, max(start, min(len(text), at + reach + LEAST))):
            start = m.start()
            if start < dull:  # in a long run that was judged from an earlier word on: only what this word begins is new
                lines, reported = [(start, dull)], novel([(start, dull)], piece)
            else:
                lines = block_lines(text, start, CANDIDATE.match(text, start).end())
                reported = None
            while True:
                start, end = lines[0][0], lines[-1][1]
                if all(known(*x) for x in lines):
                    follow = True
                elif follow := novel(lines) if reported is None else reported:
                    found.append((start, end, "novel"))
                    taken = end
                elif len(lines) == 1 and end - start > whole:
                    dull = end
                reported, gap = None, GAP.match(text, end)
                after = follow and gap and CANDIDATE.match(text, gap.end())
                if not after:
                    break
                lines = block_lines(text, *after.span())
            start = end
    # Runs before a word: each is judged once, as the forward pass may have left out what lies far from a word before it.
    runs = [m.span() for m in CANDIDATE.finditer(text, 0, near[-1][0])]
    ends, judged = [e for _, e in runs], set()
    for at, _ in near:
        k = bisect_right(ends, at) - 1
        while k >= 0 and ends[k] >= at - reach and k not in judged:
            judged.add(k)
            lines = lines_above(runs, k, text)
            judged.update(range(k - len(lines) + 1, k))
            start, end = lines[0][0], lines[-1][1]
            if not all(known(*x) for x in lines) and not any(a < end and start < b for a, b, _ in found) and novel(lines):
                found.append((start, end, "novel"))
            k -= len(lines)
    return found


def scan_text(text: str | None, novelty: Novelty | None = None) -> tuple[list[tuple[int, int, str]], list[tuple[int, int, str]]]:
    """Base spans; all spans, by start and then kind."""
    if not text:
        return [], []
    base = base_spans(text)
    return base, sorted(base + novel_spans(text, base, novelty), key=lambda x: (x[0], KINDS.index(x[2])))


def written(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


SCANNED = "doc_id bigint, n_assign bigint, n_access bigint, n_hex bigint, n_novel bigint, base_sha256 string, spans string"


def scan(docs: DataFrame, primer: str | None = None) -> DataFrame:
    """One row a document: counts by kind, digest of the base spans, all spans. primer: the dictionary; by default the corpus's."""
    primed = docs.sparkSession.sparkContext.broadcast(identifier_primer(docs) if primer is None else primer)  # at most 4000 short words

    def run(batches):
        novelty = novelty_of(primed.value)
        for batch in batches:
            for part in slices(batch, "text"):
                rows = []
                for text in part.column("text"):
                    base, spans = scan_text(text.as_py(), novelty)
                    kinds = [k for *_, k in spans]
                    rows.append((*(kinds.count(k) for k in KINDS), hashlib.sha256(written(base).encode()).hexdigest(), written(spans)))
                columns = list(zip(*rows)) or [[]] * 6
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), *(pa.array(c, pa.int64()) for c in columns[:4]), *(pa.array(c, pa.string()) for c in columns[4:])], names=[x.split()[0] for x in SCANNED.split(", ")])

    return docs.select(F.col("doc_id").cast("bigint"), "text").mapInArrow(released(run), SCANNED)


def mask_text(text: str | None, novelty: Novelty | None = None) -> str | None:
    """The text with every reported span replaced by [SECRET]; overlapping spans become one."""
    if not text:
        return text
    out, at = [], 0
    for a, b, _ in scan_text(text, novelty)[1]:
        if a >= at:
            out += [text[at:a], "[SECRET]"]
        at = max(at, b)
    return "".join(out) + text[at:] if out else text


def mask(docs: DataFrame, primer: str | None = None) -> DataFrame:
    """docs with secrets masked in text and n_chars (where it is a column) as of the masked text."""
    names = docs.columns
    primed = docs.sparkSession.sparkContext.broadcast(identifier_primer(docs) if primer is None else primer)

    def run(batches):
        novelty = novelty_of(primed.value)
        for batch in batches:
            for part in slices(batch, "text"):
                texts = [mask_text(x, novelty) for x in part.column("text").to_pylist()]
                fresh = {"text": pa.array(texts, pa.string()), "n_chars": pa.array([None if x is None else len(x) for x in texts], pa.int64())}
                yield pa.RecordBatch.from_arrays([fresh.get(c, part.column(c)) for c in names], names=names)

    return (docs.withColumn("n_chars", F.col("n_chars").cast("bigint")) if "n_chars" in names else docs).mapInArrow(released(run), docs.schema if "n_chars" not in names else docs.withColumn("n_chars", F.col("n_chars").cast("bigint")).schema)


def op9_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))


QUERIES = {"op9_secret_scan": op9_secret_scan}
ORACLES: dict = {}
