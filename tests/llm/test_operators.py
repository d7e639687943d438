"""Each operator against brute force, on planted cases, nulls, empty and repeated rows, long texts and extra columns."""

import hashlib
import random
import zlib
from collections import Counter

import numpy as np
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from filterfleet.llm import byte_bpe, components, language_model, quality_rules, registry, secret_scan, shingle_join, source_mix, spot_fingerprints, suffix_array, suffix_trees, token_files
from tests.conftest import SF

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
WORDS = "amber basin cedar delta ember fjord grove haven inlet jetty knoll ledge marsh north ocean plain quarry ridge shore tundra".split()


def prose(seed, n):
    rng = random.Random(str(seed))
    return " ".join(rng.choice(WORDS) + str(rng.randint(0, 40)) for _ in range(n))


def frame(spark, texts, langs=None, sources=None):
    rows = [(i, t, (langs or ["en"] * len(texts))[i], (sources or ["a"] * len(texts))[i], None if t is None else len(t)) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and very long texts, repeats, ties, accents, near copies, shared passages."""
    shared, base = prose("shared", 60), prose("base", 200)
    near = base.split()
    near[100] = "changed"
    texts = [None, "", "   \n\t ", "one", "one two three four", base, base, " ".join(near), prose(1, 50) + " " + shared, shared + " " + prose(2, 50), prose(3, 20000), "é ñ 日本 " * 30, "x" * 5000, "a b " * 300, base.upper(), "THE END\nTHE END\nTHE END"]
    return frame(spark, texts, sources=[None, "a"] * 8).withColumn("key", F.lit("clash")).withColumn("size", F.lit("clash")).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def texts_of(df):
    return {r.doc_id: r.text for r in df.select("doc_id", "text").collect()}


# --- quality rules


def brute_repeats(words):
    seen = Counter(zip(words, words[1:], words[2:]))
    marked = {i + k for i in range(len(words) - 2) if seen[tuple(words[i : i + 3])] > 1 for k in range(3)}
    return len(marked)


def test_quality_counts(spark, odd):
    for r in quality_rules.features(odd).collect():
        text = texts_of(odd)[r.doc_id] or ""
        words = [w for w in text.replace("\t", " ").replace("\n", " ").split(" ") if w]
        lines = [x for x in text.split("\n") if x.strip(" \t")]
        assert (r.n_words, r.word_chars, r.n_repeat_words) == (len(words), sum(map(len, words)), brute_repeats(words))
        assert r.n_dup_lines == len(lines) - len(set(lines)) and r.n_symbols == sum(c in "#*$%&|<>" for c in text)


def test_quality_verdicts_follow_the_group(spark, empty):
    clean = [prose(i, 80) for i in range(60)]
    noisy = [" ".join(w + "%%%" for w in prose(99, 80).split())]
    got = {r.doc_id: r for r in quality_rules.quality_rules(frame(spark, clean + noisy + ["short"])).collect()}
    assert all(got[i].kept for i in range(60)) and not got[60].kept and not got[60].base_failed and got[61].base_failed
    usual = quality_rules.quality_rules(frame(spark, [" ".join(w + "%" for w in x.split()) for x in clean]))
    assert usual.where("not kept").count() == 0  # what is usual in a group is no fault
    assert quality_rules.quality_rules(empty).count() == 0


def test_sketches_merge(spark):
    counted = quality_rules.features(frame(spark, [prose(i, 60 + i) for i in range(40)], sources=["a", "b"] * 20))
    parts = quality_rules.sketches(counted)
    whole = quality_rules.sketches(counted.withColumn("source", F.lit("all")))
    key = lambda d: sorted((r.lang, r.rate, r.bucket, r.n) for r in d.collect())
    assert key(quality_rules.merge(parts, "lang")) == key(whole)


# --- byte BPE, token files


def library(name):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(byte_bpe.vocabulary_path(name))


def test_bpe_equals_the_library(spark, odd, empty):
    path, lib = byte_bpe.vocabulary_path("byte_bpe_50k.json"), library("byte_bpe_50k.json")
    rng = random.Random(5)
    hard = ["aaaa" * 40, "!?" * 300, "<|endoftext|>a<|endoftext|>", "\x1c\x85 　 don't I'LL", "👩‍👩‍👧 é"] + ["".join(rng.choice("ab \n!é1' 日s_") for _ in range(40)) for _ in range(200)]
    bpe = byte_bpe.loaded(path)
    for text in hard:
        want = lib.encode(text, add_special_tokens=False).ids
        assert bpe.encode(text).tolist() == want and bpe.decode(want) == lib.decode(want, skip_special_tokens=False)
    texts = texts_of(odd)
    tokens = byte_bpe.encode(odd.withColumn("ids", F.lit(1)), path)
    for r in byte_bpe.decode(tokens, path).collect():
        assert r.decoded == (texts[r.doc_id] or "") and r.key == "clash"
    for r in byte_bpe.digests(odd, path).collect():
        ids = np.asarray(lib.encode(texts[r.doc_id] or "", add_special_tokens=False).ids, "<u4")
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), hashlib.sha256(ids.tobytes()).hexdigest(), hashlib.sha256((texts[r.doc_id] or "").encode()).hexdigest())
    assert byte_bpe.digests(empty, path).count() == 0


def brute_expand(seq, rules, first):
    out, stack = [], [int(x) for x in reversed(seq)]
    while stack:
        x = stack.pop()
        if x < first:
            out.append(x)
        else:
            stack += [int(rules[x - first][1]), int(rules[x - first][0])]
    return out


def test_pair_grammar():
    rng, first, least = np.random.default_rng(1), 1 << 16, 8
    cases = [np.array([], np.uint32), np.array([7], np.uint32), np.full(5000, 3, np.uint32), np.tile(rng.integers(0, 50, 37), 300).astype(np.uint32), rng.integers(0, 40_000, 5000).astype(np.uint32)]
    cases += [(rng.zipf(1.3, 30_000) % 500).astype(np.uint32), np.array([1, 2, 1] * 60 + [7] * 33, np.uint32)]
    for ids in cases:
        seq, rules, lengths = token_files.replace_pairs(ids, first, least)
        assert brute_expand(seq, rules, first) == ids.tolist()
        assert lengths.tolist() == [len(brute_expand([first + k], rules, first)) for k in range(len(rules))]
        pairs = Counter(zip(seq.tolist(), seq[1:].tolist()))
        assert not pairs or max(pairs.values()) < least  # none is left
        before = Counter(zip(ids.tolist(), ids[1:].tolist())).most_common()
        if before and before[0][1] >= least:  # the most frequent pair is among the rules
            assert any((a, b) in map(tuple, rules.tolist()) for (a, b), n in before if n == before[0][1])
        assert (token_files.read_ids(seq, rules, lengths, first) == ids).all()
        for a, b in ((0, 0), (0, 1), (len(ids) // 3, len(ids) // 2), (max(len(ids) - 2, 0), len(ids)), *np.sort(rng.integers(0, len(ids) + 1, (40, 2))).tolist()):
            assert (token_files.read_ids(seq, rules, lengths, first, a, min(b, len(ids))) == ids[a:b]).all()


def test_pair_ranks_count_every_pair():
    rng = np.random.default_rng(4)
    for seq in (rng.zipf(1.4, 4000).astype(np.int64) % 300, rng.integers(0, 1 << 30, 3000).repeat(9)):
        pairs, ranks = token_files.pair_ranks(seq.astype(np.int64), 5)
        want = {p for p, n in Counter(zip(seq.tolist(), seq[1:].tolist())).items() if n >= 5}
        assert set(map(tuple, pairs.tolist())) == want
        assert [tuple(pairs[r - 1].tolist()) if r else None for r in ranks[1:-1]] == [p if p in want else None for p in zip(seq.tolist(), seq[1:].tolist())]


def test_token_files(spark, odd, empty):
    path, lib = byte_bpe.vocabulary_path("word_bpe_49k.json"), library("word_bpe_49k.json")
    files = token_files.write_files(odd, path, block_tokens=500)
    got, start = {r.doc_id: r for r in token_files.read_files(files).collect()}, 0
    want = {}
    for doc_id, text in sorted(texts_of(odd).items()):
        ids = want[doc_id] = np.asarray(lib.encode(text or "", add_special_tokens=False).ids + [1], "<u4")
        assert (got[doc_id].start, got[doc_id].n_tokens, got[doc_id].ids_crc32) == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)
    some = token_files.read_documents(files, spark.createDataFrame([(0,), (5,), (10,), (99,)], "doc_id long")).collect()
    assert {r.doc_id: bytes(r.ids) for r in some} == {k: want[k].tobytes() for k in (0, 5, 10)}
    assert token_files.read_files(token_files.write_files(empty, path)).count() == 0
    lost = spark.createDataFrame([(None, "a b"), (-(2**63), "c"), (None, "d"), (4, "e")], "doc_id long, text string")
    rows = token_files.read_files(token_files.write_files(lost, path)).orderBy("start").collect()
    assert [r.doc_id for r in rows] == [None, None, -(2**63), 4] and rows[-1].start + rows[-1].n_tokens == sum(r.n_tokens for r in rows)


def test_pieces_encode_apart():
    encoder, lib = token_files.PieceEncoder(byte_bpe.vocabulary_path("word_bpe_49k.json"), most=64), library("word_bpe_49k.json")
    rng = random.Random(6)
    texts = ["é x", "ΑΣ ΣΑ", "0 10 a0b", "<|endoftext|>x", "it's"] + ["".join(rng.choice("ab \n0é́'Σ日st_") for _ in range(30)) for _ in range(300)]
    pool = ["'s", "'RE", "'", "a", "B", "É", "İ", "ı", "ß", "ẞ", "ſ", "ς", "µ", "ª", "²", "½", "٣", "😀", "́", "\xa0", "\x85", "\u3000", "\x1c", " ", " ", "\t", "<|startoftext|>", "<|", "##", "9", "ĳ", "ŉ", "ž", "\x00", "\u200b", "the", "Ⅷ", "한"]
    texts += ["".join(rng.choice(pool) for _ in range(rng.randint(0, 30))) for _ in range(2000)]
    for start in range(0, len(texts), 50):
        part = texts[start : start + 50]
        for text, packed in zip(part, encoder.encode_batch(part)):
            assert np.frombuffer(packed, "<u4").tolist() == lib.encode(text, add_special_tokens=False).ids + [1]
        assert max(len(encoder), len(encoder.older)) <= 32


def test_piece_bounds_follow_the_splitting_rule():
    rng = random.Random(12)
    for _ in range(3000):
        text = "".join(rng.choices("'''''stmdrevlaé9 0\n.-\"", k=rng.randint(0, 20)))
        raw = text.encode()
        starts, ends = token_files.piece_bounds(np.frombuffer(raw, np.uint8))
        assert [raw[a:b].decode() for a, b in zip(starts.tolist(), ends.tolist())] == token_files.PIECES(text)


def test_new_pieces_do_not_ask_the_library():
    encoder, lib = token_files.PieceEncoder(byte_bpe.vocabulary_path("word_bpe_49k.json"), bits=6), library("word_bpe_49k.json")
    encoder.MOST = 100

    def ask(piece):
        assert len(piece.encode()) > 16
        return lib.model.tokenize(piece)

    encoder.tokenize = ask
    rng, letters = random.Random(9), "etaoinshrdlucmfwypvbgkqjxzéßøž"
    texts = [" ".join("".join(rng.choices(letters, k=rng.randint(1, 16))) for _ in range(60)) for _ in range(40)]
    texts = [" ".join(w for w in x.split() if len(w.encode()) <= 16) for x in texts]
    texts += ["aaaaaaaaaaaaaaaa aaa banana ananan", "it's 'SHE'LL' they're''s x'v 've'd 'm3 'd'", "0123456789" * 40, "!!!! ?!?! ---- '''' ''s", None, "", "internationalization's " * 30, "日本 Été “x” " * 20]
    for _ in range(2):  # the second time some pieces are held; the small table drops others
        for text, packed in zip(texts, encoder.encode_batch(texts)):
            assert np.frombuffer(packed, "<u4").tolist() == lib.encode(text or "", add_special_tokens=False).ids + [1]
    assert encoder.merges.ordered and encoder.encode_batch([]) == []
    encoder.merges.ordered, encoder.tokenize, encoder.table = False, lib.model.tokenize, token_files.PieceTable(6)  # by the library alone
    assert encoder.encode_batch(texts[:60:7]) == token_files.PieceEncoder(byte_bpe.vocabulary_path("word_bpe_49k.json")).encode_batch(texts[:60:7])


# --- shingle join


def brute_classes(texts, width=5, percent=75):
    sets = {}
    for k, t in texts.items():
        words = (t or "").encode().lower().split()
        sets[k] = {tuple(words[i : i + width]) for i in range(max(1, len(words) - width + 1))} if words else set()
    label = {k: k for k in sets}

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                label[y] = x
    return {k: (len(s), find(k)) for k, s in sets.items()}


def test_shingle_join(spark, odd, empty):
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in shingle_join.similarity_classes(odd).collect()}
    assert got == brute_classes(texts_of(odd)) and got[7][1] == 5
    assert shingle_join.similarity_classes(empty).count() == 0


def test_shingle_join_chains_and_groups(spark):
    base, rng, texts = prose("b", 120).split(), random.Random(2), []
    for i in range(60):  # a chain that drifts away, a crowd around one text, and texts that share most of a passage
        base[rng.randrange(120)] = f"new{i}"
        texts.append(" ".join(base))
    crowd = prose("c", 100).split()
    for i in range(60):
        texts.append(" ".join(f"edit{i}" if k == i else w for k, w in enumerate(crowd)))
    texts += [prose("p", 80) + " " + prose(("tail", i), 5 + i) for i in range(40)]
    df = frame(spark, texts)
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in shingle_join.similarity_classes(df).collect()} == brute_classes(texts_of(df))


def test_shingle_join_without_ids(spark):
    text = prose(9, 40)
    rows = shingle_join.similarity_classes(spark.createDataFrame([(None, text), (7, text), (None, "one"), (3, text + " more"), (None, None)], "doc_id long, text string")).collect()
    assert sorted((r.doc_id or 0, r.component_id or 0) for r in rows) == [(0, 0), (0, 0), (0, 0), (3, 3), (7, 3)]
    assert all(r.set_id is None and r.component_id is None for r in rows if r.doc_id is None)


def test_parity_sketches_never_rule_out_a_match():
    rng = np.random.default_rng(4)
    for _ in range(200):
        a, b = (np.unique(rng.integers(0, 400, rng.integers(1, 300)).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) for _ in range(2))
        assert shingle_join.least_difference(shingle_join.parity_sketch(a), shingle_join.parity_sketch(b)) <= len(np.setxor1d(a, b))


def test_components(spark):
    rng = random.Random(8)
    links = [(rng.randrange(200), rng.randrange(200)) for _ in range(120)] + [(300 + i, 301 + i) for i in range(40)] + [(500, 500 + i) for i in range(1, 60)]
    label = {}
    for a, b in links:
        label.setdefault(a, a), label.setdefault(b, b)
    changed = True
    while changed:
        changed = False
        for a, b in links:
            low = min(label[a], label[b])
            changed |= label[a] != low or label[b] != low
            label[a] = label[b] = low
    got = {r.node: r.label for r in components.components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert all(got[k] == v for k, v in label.items() if k in got) and {k for k in label if label[k] != k} <= set(got)


# --- substring dedup


def brute_removed(seqs, least):
    seen = Counter(s[i : i + least] for s in seqs for i in range(len(s) - least + 1))
    out = []
    for s in seqs:
        gone = [False] * len(s)
        for i in range(len(s) - least + 1):
            if seen[s[i : i + least]] > 1:
                gone[i : i + least] = [True] * least
        out.append(gone)
    return out


def test_suffix_trees(spark, odd, empty):
    texts = texts_of(odd)
    seqs = {k: tuple((t or "").encode().split()) for k, t in texts.items()}
    want = dict(zip(seqs, brute_removed(list(seqs.values()), 35)))
    for r in suffix_trees.deduplicated(odd).collect():
        kept = b" ".join(w for w, g in zip(seqs[r.doc_id], want[r.doc_id]) if not g)
        assert (r.n_words, r.n_removed, r.kept_sha256) == (len(seqs[r.doc_id]), sum(want[r.doc_id]), hashlib.sha256(kept).hexdigest())
    assert suffix_trees.deduplicated(empty).count() == 0


def test_suffix_array(spark, odd, empty):
    seqs = {k: (t or "").encode() for k, t in texts_of(odd).items()}
    want = dict(zip(seqs, brute_removed(list(seqs.values()), 200)))
    for r in suffix_array.deduplicated(odd).collect():
        gone, raw = want[r.doc_id], seqs[r.doc_id]
        spans = sum(g and not (i and gone[i - 1]) for i, g in enumerate(gone))
        assert (r.n_bytes, r.n_removed, r.n_spans) == (len(raw), sum(gone), spans)
        assert r.kept_sha256 == hashlib.sha256(bytes(b for b, g in zip(raw, gone) if not g)).hexdigest()
    assert suffix_array.deduplicated(empty).count() == 0


@pytest.mark.parametrize("module, total", [(suffix_trees, "n_words"), (suffix_array, "n_bytes")])
def test_crowded_grams(spark, module, total):
    """A common passage amid ever new text, and some of it repeated: longer grams find what shorter ones do."""
    line = prose("line", 30)
    texts = [prose(("a", i), 40) + " " + line + " " + prose(("b", i), 40) for i in range(40)] + [prose(("a", 3), 40) + " " + line + " " + prose(("c", i), 30) for i in range(3)]
    df = frame(spark, texts)
    usual = sorted(map(tuple, module.deduplicated(df).collect()))
    assert usual == sorted(map(tuple, module.deduplicated(df, crowd=0).collect())) == sorted(map(tuple, module.deduplicated(df, crowd=5).collect()))
    least = 35 if module is suffix_trees else 200
    seqs = [tuple(t.encode().split()) if module is suffix_trees else t.encode() for t in texts]
    gone = brute_removed(seqs, least)
    assert [(r.doc_id, r.n_removed) for r in module.deduplicated(df, crowd=0).orderBy("doc_id").collect()] == [(i, sum(g)) for i, g in enumerate(gone)] and sum(map(sum, gone)) > 0


@pytest.mark.parametrize("depth", [1, 2, 3, 4, 9, 10, 50])
def test_suffix_ranks(depth):
    rng = np.random.default_rng(depth)
    for n in (0, 1, 2, 3, 4, 5, 30, 301):
        for text in (rng.integers(1, 3, n), rng.integers(1, 200, n), np.ones(n, np.int64)):
            order = np.argsort(suffix_ranks := suffix_array.suffix_ranks(text, depth))
            heads = [tuple(text[i : i + depth]) for i in order.tolist()]
            assert heads == sorted(heads) and sorted(suffix_ranks.tolist()) == list(range(n))


def test_long_texts_in_pieces(monkeypatch):
    from filterfleet.llm import anchors

    elements = anchors.byte_elements(prose(5, 3000).encode() * 2)
    whole = anchors.anchors(elements, 200, 64)
    monkeypatch.setattr(anchors, "MOST_ELEMENTS", 5000)
    parts = anchors.anchors(elements, 200, 64)
    assert whole[4].sum() == parts[4].sum() == len(elements) - 199


def test_repeated_and_null_ids(spark):
    text = prose(9, 100)
    df = spark.createDataFrame([(1, text), (1, text + " more"), (None, text), (None, None), (2, prose(10, 100)), (2, prose(10, 100))], "doc_id long, text string")
    for module, total in ((suffix_trees, "n_words"), (suffix_array, "n_bytes")):
        rows = module.deduplicated(df).collect()
        assert len(rows) == 6 and sum(r.doc_id is None for r in rows) == 2
        assert sum(r.n_removed == r[total] for r in rows) == 5  # the null text has nothing; of the longer copy a rest stays
    assert shingle_join.similarity_classes(df).count() == 6
    assert spot_fingerprints.compare_with_next(df).count() == 6
    assert source_mix.decisions(df.withColumn("source", F.lit(None).cast("string"))).count() == 6
    assert token_files.read_files(token_files.write_files(df, byte_bpe.vocabulary_path("word_bpe_49k.json"))).count() == 6


# --- language model


def brute_model(texts):
    """Interpolated modified Kneser-Ney from dictionaries: a function from (three bytes before, byte) to a probability."""
    levels = {4: Counter()}
    for text in texts:
        data = [255] * 3 + list(text.encode())
        levels[4].update(tuple(data[i - 3 : i + 1]) for i in range(3, len(data)))
    for order in (3, 2, 1):
        levels[order] = Counter(g[1:] for g in levels[order + 1])
    cuts, follow = {}, {}
    for order, level in levels.items():
        n = Counter(level.values())
        y = n[1] / (n[1] + 2 * n[2]) if n[1] else 0.5
        cuts[order] = [0] + [min(max(k - (k + 1) * y * n[k + 1] / n[k] if n[k] else k / 2, 0.05), k - 0.05) for k in (1, 2, 3)]
        for g, c in level.items():
            follow.setdefault(g[:-1], []).append(c)

    def prob(gram):
        if not gram:
            return 1 / 256
        order, after = len(gram), follow.get(gram[:-1])
        if after is None:
            return prob(gram[1:])
        c = levels[order][gram]
        spared = sum(cuts[order][min(x, 3)] for x in after)
        return (c - cuts[order][min(c, 3)] + spared * prob(gram[1:])) / sum(after)

    return prob


def text_frame(spark, texts):
    return spark.createDataFrame([(t,) for t in texts], "text string")


def test_model_is_a_distribution(spark):
    texts = [prose(i, 120) for i in range(12)] + ["été 日本語 \U000e0041\U0001f3f4" * 3]
    fitted, brute = language_model.fit(language_model.gram_counts(text_frame(spark, texts))), brute_model(texts)
    pieces = []
    for kind, frame_, column in (("prob", fitted.probs, "prob"), ("weight", fitted.backoff, "weight")):
        rows = frame_.collect()
        pieces += [(kind, o, *(np.array([r[c] for r in rows if r.ord == o], t) for c, t in (("gram", np.uint32), (column, np.float64)))) for o in (1, 2, 3, 4)]
    model = language_model.Part.of(pieces)
    rng = np.random.default_rng(0)
    for head in (int.from_bytes(b"\xff\xff\xff"), int.from_bytes(b"amb"), 0xABCDEF):
        gram = np.uint32(head) << np.uint32(8) | np.arange(256, dtype=np.uint32)
        assert model.prob(gram).sum() == pytest.approx(1, abs=1e-9) and (model.prob(gram) > 0).all()
    anything = np.concatenate([language_model.grams(texts)[0][::50], rng.integers(0, 2**32, 300).astype(np.uint32)])
    assert model.prob(anything) == pytest.approx([brute(tuple(int(g).to_bytes(4))) for g in anything], rel=1e-9)


def test_any_alphabet(spark):
    texts = ["\U000e0067\U000e0062\ufe0f\U0010fffd" * 20, "漢字かな交じり文" * 10, "ασδφ" * 30, "\x00\x01" * 5]
    docs = frame(spark, texts)
    labels = spark.createDataFrame([(i, 1, 0) for i in range(4)], "doc_id long, quality int, toxic int")
    assert all(r.perplexity < 3 and r.kept for r in language_model.judged(docs, labels).collect())


def test_fences_of_many_languages(spark):
    texts, langs = [prose(i, 12) for i in range(120)], [f"l{i % 60}" for i in range(118)] + [None, None]
    docs, labels = frame(spark, texts, langs), spark.createDataFrame([(i, 1, 0) for i in range(120)], "doc_id long, quality int, toxic int")
    rows = language_model.judged(docs, labels, least_group=1).collect()
    assert len(rows) == 120 and len({r.fence for r in rows}) == 61 and all(r.fence >= r.perplexity for r in rows)


def test_classifier_on_labels(spark, odd, empty):
    docs, labels = (spark.read.parquet(f"{SF.replace('0.001', '0.01')}/{t}.parquet") for t in ("documents", "labels"))
    rows = language_model.judged(docs, labels).join(labels, "doc_id").collect()
    kept = lambda q: np.mean([r.kept for r in rows if r.quality == q])
    assert kept(1) > 0.97 and kept(0) < 0.35
    got = {r.doc_id: r for r in language_model.judged(odd, labels.where("doc_id in (3, 4, 5)")).collect()}
    assert len(got) == 16 and not got[0].kept and not got[1].kept
    assert language_model.judged(empty, labels).count() == 0
    assert language_model.judged(odd, labels.limit(0)).where("kept").count() == 14
    assert language_model.accepted(docs, labels).columns == docs.columns


def test_low_quality_does_not_pass_by_the_margin(spark):
    docs, labels = (spark.read.parquet(f"{SF.replace('0.001', '0.01')}/{t}.parquet") for t in ("documents", "labels"))
    rows = language_model.judged(docs, labels).join(labels, "doc_id").collect()
    kept = lambda q: np.mean([r.kept for r in rows if r.quality == q])
    assert kept(0) < 0.03 and kept(1) > 0.97


def test_sharded_scores_equal_brute_force(spark):
    docs, labels = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "labels"))
    sample = [r.text for r in language_model.trusted_sample(docs, labels, 30, 2000).collect()]
    brute = brute_model(sample)
    fitted = language_model.train(docs, labels, most_docs=30, most_chars=2000)
    scores = {r.doc_id: r for r in language_model.perplexities(docs, fitted, shards=3).collect()}
    texts = {k: t for k, t in texts_of(docs).items() if t and len(t) < 3000}
    for doc_id, text in list(texts.items())[:40]:
        data = b"\xff\xff\xff" + text.encode()
        logs = [np.log(brute(tuple(data[i - 3 : i + 1]))) for i in range(3, len(data))]
        assert scores[doc_id].n_grams == len(logs) and scores[doc_id].perplexity == pytest.approx(np.exp(-np.mean(logs)), rel=1e-4)


# --- mixing


def test_mix(spark, odd, empty, tmp_path):
    sizes = [5, 50, 7, 30, 9, 80, 11, 3, 60, 20]
    df = frame(spark, [prose(i, n) for i, n in enumerate(sizes * 20)], sources=[["a", "b", "c", None][i % 4] for i in range(200)])
    rows = source_mix.decisions(df).collect()
    total = sum(sizes) * 20
    by = {}
    for r in rows:
        by.setdefault(r.source, []).append(r)
        assert 0 <= r.copies <= 3 and r.source_size == sum(x.size for x in rows if x.source == r.source)
    assert sum(g[0].target for g in by.values()) == pytest.approx(total)
    for group in by.values():
        assert abs(sum(r.size * r.copies for r in group) - group[0].target) <= 2 * max(sizes)
    plain = lambda found: sorted(map(repr, found))
    assert plain(rows) == plain(source_mix.decisions(df.repartition(3)).collect())
    mixed = source_mix.mixed(df)
    assert mixed.columns == df.columns and mixed.count() == sum(r.copies for r in rows)
    of = {r.doc_id: r for r in rows}
    for r in rows:
        before = sum(x.size for x in rows if x.source == r.source and (x.key, x.size) <= (r.key, r.size))
        assert r.finish == pytest.approx([(e * r.source_size + before) / r.target for e in range(r.copies)])
    want = [d for _, _, d in sorted((f, r.key, r.doc_id) for r in rows for f in r.finish)]
    assert [r.doc_id for r in mixed.collect()] == want  # partitions, and rows in them, come in order of finish time
    mixed.write.parquet(str(tmp_path / "mix"))
    files = sorted((tmp_path / "mix").glob("part-*"))
    assert [x for f in files for x in pq.read_table(f).column("doc_id").to_pylist()] == want
    assert of[want[0]].finish[0] <= of[want[-1]].finish[-1] and len(files) == 4
    clash = source_mix.mixed(odd)
    assert clash.columns == odd.columns and {(r["size"], r["key"]) for r in clash.collect()} == {("clash", "clash")}
    lost = spark.createDataFrame([(None, "a b", "s"), (None, "a b", "s"), (None, "c", None), (1, None, "s")], "doc_id long, text string, source string")
    assert source_mix.decisions(lost).count() == 4 and source_mix.mixed(lost).where("text is not null").count() >= 3
    assert source_mix.decisions(odd).count() == 16 and source_mix.decisions(empty).count() == 0 and source_mix.mixed(empty).count() == 0


def test_targets_stop_at_three_times(spark):
    rows = spark.createDataFrame([("0a", 100), ("0b", 10), ("0c", 1000)], "sid string, source_size long")
    got = {r.sid: r.target for r in source_mix.targets(rows).collect()}
    assert got["0b"] == 30 and sum(got.values()) == pytest.approx(1110)
    assert got["0c"] == pytest.approx(3 * (1110 - 30) / 4) and got["0a"] == pytest.approx((1110 - 30) / 4)


# --- fingerprints


def test_fingerprints(spark, odd, empty):
    texts = sorted(texts_of(odd).items(), reverse=True)
    got = {r.doc_id: r for r in spot_fingerprints.compare_with_next(odd).collect()}
    for (doc_id, text), (_, after) in zip(texts, texts[1:] + texts[:1]):
        text, after = text or "", after or ""
        edited = text[: len(text) - len(text) // 2] + after[: len(text) // 2]
        r, sets = got[doc_id], [spot_fingerprints.signatures(x) for x in (text, edited, after)]
        assert (r.n_chars, r.edited_sha256) == (len(text), hashlib.sha256(edited.encode()).hexdigest())
        assert r.fingerprint == spot_fingerprints.written(sets[0]) and r.edited_fingerprint == spot_fingerprints.written(sets[1])
        assert r.near_next == pytest.approx(spot_fingerprints.pruned_jaccard(sets[0], sets[2])) and 0 <= r.near_edited <= 1
    assert got[5].fingerprint == got[6].fingerprint
    assert spot_fingerprints.compare_with_next(empty).count() == 0 and spot_fingerprints.compare_with_next(odd.limit(1)).count() == 1


def brute_spots(text):
    """Chains as tuples of words: at each common word the two content words after it."""
    words = [w for w in text.replace("\t", " ").replace("\n", " ").replace("\r", " ").replace("\x0b", " ").replace("\x0c", " ").split(" ") if w]
    bare = []
    for w in words:
        low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in w)
        stripped = low.strip(".,;:!?\"'()[]{}")
        bare.append(stripped or w)
    common = set(spot_fingerprints.ANCHORS)
    chains = set()
    for i, w in enumerate(bare):
        if w in common:
            after = [x for x in bare[i + 1 :] if x not in common][:2]
            if len(after) == 2:
                chains.add((w, *after))
    return chains or set(bare) or ({text} if text else set())


def brute_likeness(a, b):
    return len(a & b) / len(a | b) if a or b else 1.0


def test_fingerprints_by_hand(spark, odd):
    rng = random.Random(21)
    pool = ["the", "The", "of,", "de", "und", "(la)", "amber", "Basin.", "cedar", "delta!", "...", "é", "ember"]
    texts = [" ".join(rng.choice(pool) for _ in range(rng.randint(0, 60))) for _ in range(60)] + [None, "", "...", "the of", "the amber"]
    for docs in (frame(spark, texts), odd):
        order = sorted(texts_of(docs).items(), reverse=True)
        got = {r.doc_id: r for r in spot_fingerprints.compare_with_next(docs).collect()}
        for (doc_id, text), (_, after) in zip(order, order[1:] + order[:1]):
            text, after = text or "", after or ""
            edited = text[: len(text) - len(text) // 2] + after[: len(text) // 2]
            mine, next_, cut = brute_spots(text), brute_spots(after), brute_spots(edited)
            assert got[doc_id].near_next == pytest.approx(brute_likeness(mine, next_)), (text, after)
            assert got[doc_id].near_edited == pytest.approx(brute_likeness(mine, cut))
            assert (got[doc_id].fingerprint == got[doc_id].edited_fingerprint) == (mine == cut)


def test_near_duplicates_by_fingerprint(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    prints = spot_fingerprints.fingerprints(docs).cache()
    sets, first = {}, {}
    for r in prints.where("n_signatures > 0").orderBy("doc_id").collect():
        if r.fingerprint not in first:
            first[r.fingerprint] = r.doc_id
            sets[r.doc_id] = spot_fingerprints.signatures(texts_of(docs)[r.doc_id])
    want = {tuple(sorted((a, b))) for a in sets for b in sets if a < b and spot_fingerprints.pruned_jaccard(sets[a], sets[b]) >= 0.75}
    assert {tuple(sorted((r.a, r.b))) for r in spot_fingerprints.near_duplicates(prints).collect()} == want


# --- secrets


def test_secrets(spark, odd, empty):
    key = "AKIA" + "ABCDEFGHIJ234567"
    text = f'x password = "correcthorsebattery" y token: short {key} deadbeefdeadbeef00 ' + 'the api key follows Zx9Qk2Lm7Rt4Vb1Nc8Yw3Hd6Jf0Ps5G and more'
    base, spans = secret_scan.scan_text(text)
    assert [k for *_, k in base] == ["assign", "access", "hex"] and [k for *_, k in spans] == ["assign", "access", "hex", "novel"]
    assert text[spans[0][0] : spans[0][1]] == 'password = "correcthorsebattery' and text[spans[1][0] : spans[1][1]] == key
    assert secret_scan.scan_text("password: secret: abcdefghijklmnop")[0] == []  # the word after the colon is taken, and is short
    assert secret_scan.scan_text("the token configuration-settings-environment-path")[1] == []
    got = {r.doc_id: r for r in secret_scan.scan(odd).collect()}
    assert len(got) == 16 and got[0].base_sha256 == hashlib.sha256(b"").hexdigest() and all(r.spans == "" for r in got.values())
    masked = secret_scan.mask(frame(spark, [text, None, "plain"])).orderBy("doc_id").collect()
    assert masked[0].text.count("[SECRET]") == 4 and masked[0].n_chars == len(masked[0].text) and masked[1].text is None and masked[2].text == "plain"
    assert secret_scan.scan(empty).count() == 0 and secret_scan.mask(empty).count() == 0


@pytest.mark.parametrize("letters", ["0123456789abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", "0123456789ABCDEF", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"])
def test_keys_of_few_classes(letters):
    rng = random.Random(letters)
    for size in (20, 32, 40):
        for before in ("Authorization: Bearer ", "cookie: ", "the api key follows "):
            key = "".join(rng.choice(letters) for _ in range(size))
            text = f"{' '.join(WORDS)} {before}{key} {' '.join(reversed(WORDS))}"
            at = text.index(key)
            assert (at, at + size, "novel") in secret_scan.scan_text(text)[1]
            assert key not in secret_scan.mask_text(text)


@pytest.mark.parametrize("letters", ["ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/", "0123456789abcdefghijklmnopqrstuvwxyz", "0123456789ABCDEF"])
def test_long_keys_are_taken_whole(letters):
    rng = random.Random(letters)
    key = lambda n: "".join(rng.choice(letters) for _ in range(n))
    for size in (520, 1600, 5000):
        run = key(size)
        text = f"{prose(1, 30)} credential {run} {prose(2, 30)}"
        assert secret_scan.mask_text(text) == f"{prose(1, 30)} credential [SECRET] {prose(2, 30)}"
    for newline in ("\n", "\r\n", "\\n", "\n    "):
        body = newline.join([*(key(64) for _ in range(25)), key(11)])
        text = f"{prose(1, 30)}\n-----BEGIN PRIVATE KEY-----{newline}{body}{newline}-----END PRIVATE KEY-----\n{prose(2, 30)}"
        masked = secret_scan.mask_text(text)
        assert len(masked) < len(text) - len(body) + 12 and masked.endswith(prose(2, 30))
        assert not any(line[1:] in masked for line in body.split(newline))
    parts = [key(40), key(30), key(50)]
    assert secret_scan.mask_text(f"session {'  '.join(parts)} and more") == "session [SECRET]  [SECRET]  [SECRET] and more"


def test_keys_before_the_word():
    rng = random.Random(8)
    key = lambda n: "".join(rng.choice("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789") for _ in range(n))
    for n in (20, 40, 600):
        run = key(n)
        assert secret_scan.mask_text(f"{prose(1, 30)} {run} is the api key {prose(2, 9)}") == f"{prose(1, 30)} [SECRET] is the api key {prose(2, 9)}"
        assert secret_scan.mask_text(f"{run} {prose(3, 40)} token") == f"{run} {prose(3, 40)} token"  # too far off
    lines = [key(64) for _ in range(12)] + [key(20)]
    text = f"{prose(1, 30)}\n" + "\n".join(lines) + f"\nabove is the private key {prose(2, 9)}"
    assert secret_scan.mask_text(text) == f"{prose(1, 30)}\n[SECRET]\nabove is the private key {prose(2, 9)}"


def test_novelty_by_hand():
    """Against a plain reading: one word of context, one run, compressed sizes with and without it."""
    import zstandard

    def size(data):
        primed = zstandard.ZstdCompressionDict(secret_scan.PRIMER.encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        return len(zstandard.ZstdCompressor(level=3, dict_data=primed, write_content_size=False).compress(data.encode()))

    rng, seen = random.Random(11), set()
    for trial in range(300):
        run = "".join(rng.choice([*(rng.choice("ab019Z_") for _ in range(2)), "name", "config", "user", "-", "path"]) for _ in range(40))[: rng.randint(16, 60)]
        before, gap = prose(trial, 12), "x " * rng.randint(0, 30)
        text = f"{before} token {gap}{run} {prose(-trial, 12)}"
        at = text.index(run)
        whole = not any(c.isalnum() or c in "+/_=~.-" for c in (text[at - 1], text[at + len(run)]))
        near = len(gap) + 1 <= 48
        rate = (size(f"{text[max(0, at - 400) : at]}\n{text[at + len(run) :][:400]}\n{run}") - size(f"{text[max(0, at - 400) : at]}\n{text[at + len(run) :][:400]}\n")) / len(run)
        want = whole and near and rate >= 0.6
        seen.add(want)
        base, spans = secret_scan.scan_text(text)
        if not base:
            assert (spans == [(at, at + len(run), "novel")]) == want, (text, rate)
    assert seen == {True, False}


def test_base_patterns_by_hand():
    """Against a scan by character: names, signs, then the longest run."""
    letters, tail = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz", "+/_=.-"

    def assigned(text):
        low, at, out = "".join(c.lower() if c.isascii() else c for c in text), 0, []
        while at < len(text):
            for name in ("password", "passwd", "secret", "token", "api_key", "apikey"):
                if low.startswith(name, at):
                    k = at + len(name)
                    k += text[k : k + 1] in ("'", '"')
                    while text[k : k + 1] == " ":
                        k += 1
                    if text[k : k + 1] in (":", "="):
                        k += 1
                        while text[k : k + 1] == " ":
                            k += 1
                        k += text[k : k + 1] in ("'", '"')
                        end = k
                        while end < len(text) and text[end] in letters + tail:
                            end += 1
                        if end > k:
                            out += [(at, end, "assign")] if end - k >= 12 else []
                            at = end - 1
                            break
            at += 1
        return out

    def runs(text, head, chars, least, kind):
        at, out = 0, []
        while at < len(text):
            end = at + len(head)
            if text.startswith(head, at) and text[end : end + 1] and text[end] in chars:
                while end < len(text) and text[end] in chars:
                    end += 1
                out += [(at, end, kind)] if end - at >= least else []
                at = end
            else:
                at += 1
        return out

    rng = random.Random(12)
    pool = ["password", "Secret", "TOKEN", "api_key", "apikey", "passwd", "\u017fecret", "=", ":", " ", "'", '"', "AKIA", "AKIAAKIA", "ABCDEF0123456789", "deadbeef", "0011", "x+/_-", "\n", "é", "\u212a", "abcdefabcdef", "zzzzzzzzzzzzzz"]
    for _ in range(1500):
        text = "".join(rng.choice(pool) for _ in range(rng.randint(1, 40)))
        upper = letters[10:36] + letters[:10]
        want = assigned(text) + runs(text, "AKIA", upper, 18, "access") + runs(text, "", "0123456789abcdef", 16, "hex")
        order = ("assign", "access", "hex")
        assert secret_scan.base_spans(text) == sorted(want, key=lambda x: (x[0], order.index(x[2]))), text


def test_identifier_primer(spark, odd):
    texts = ["userName user_name UserID " * 3, "key=" + "qwertyuiopasdfgh" * 2, "ab Abc abcdefghijkl abcdefghijklm"]
    parts = secret_scan.identifier_primer(frame(spark, texts), most=50).removesuffix(" " + secret_scan.PRIMER).split()
    assert sorted(parts) == sorted(["user", "Name", "name", "User", "key", "Abc", "abcdefghijkl"])
    assert parts[-1] == "user" and parts.index("key") < parts.index("User")  # the most frequent one last
    assert secret_scan.identifier_primer(frame(spark, [None, ""])).endswith(secret_scan.PRIMER)


def test_identifier_parts_end_where_cases_do():
    assert secret_scan.PART.findall("userName getHTTPServer parseURLs") == ["user", "Name", "get", "Server", "parse"]
    assert secret_scan.PART.findall("Abcdefghijkl Abcdefghijklm xAbcdefghijklm") == ["Abcdefghijkl"]  # one letter more is left out whole


def test_dull_runs_stay():
    for run in ("x" * 5000, "token" * 3000, "configuration-settings-environment-path-" * 40):
        assert secret_scan.scan_text(f"the token {run} of it")[1] == []
    assert secret_scan.mask_text("secret Zx9Qk2Lm7Rt4Vb1Nc8Yw3Hd6Jf0Ps5G\nThanks\nand more") == "secret [SECRET]\nThanks\nand more"


# --- queries and pipeline


def test_pipeline_on_odd_input(spark, tmp_path, odd, empty):
    """Null, empty and repeated rows through all stages, and tables without rows."""
    import corpus_pipeline

    labels = spark.createDataFrame([(i, 1, 0) for i in (3, 4, 5, 7, 8)] + [(14, 0, 0)], "doc_id long, quality int, toxic int")
    for name, docs in (("odd", odd.drop("key", "size").unionByName(spark.createDataFrame([(None, prose("base", 200), "en", "a", None), (5, prose("base", 200), "en", "a", 1)], SCHEMA))), ("empty", empty)):
        docs.write.parquet(str(tmp_path / name / "documents.parquet"))
        labels.write.parquet(str(tmp_path / name / "labels.parquet"))
        rows = corpus_pipeline.run(spark, str(tmp_path / name)).collect()
        assert all(r.n_tokens == len(r.ids) > 0 for r in rows)
        assert (name == "empty") == (not rows)


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_query_against_sql(spark, oracle, name):
    df = registry.QUERIES[name](spark, SF)
    columns, want = oracle(registry.ORACLES[name])
    assert sorted(df.columns) == columns and sorted(repr(list(r)) for r in df.select(*columns).collect()) == want


def test_pipeline(spark):
    import corpus_pipeline

    docs = before = spark.read.parquet(f"{SF}/documents.parquet")
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        docs = stage(spark, docs, SF).cache()
        if k < 4:
            assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
        if k == 1:
            classes = brute_classes(texts_of(before))
            assert sorted(r.doc_id for r in docs.collect()) == sorted({c for _, c in classes.values()})
        if k == 2:
            assert docs.count() == before.count() and not any(secret_scan.scan_text(t)[0] for t in texts_of(docs).values())
        before = docs
    lib = library("byte_bpe_50k.json")
    texts = texts_of(corpus_pipeline.mask_secrets(spark, spark.read.parquet(f"{SF}/documents.parquet"), SF))
    for r in docs.collect():
        assert r.ids == lib.encode(texts[r.doc_id], add_special_tokens=False).ids


def test_every_trusted_text_is_counted(spark):
    """4100 trusted texts, the last one of 30,000 characters: all of them are in the model's counts."""
    texts = [f"q{i:04d}" for i in range(4099)] + ["z" * 30_000]
    docs = frame(spark, texts).cache()
    labels = docs.selectExpr("doc_id", "1 as quality", "0 as toxic")
    counts = {r.gram: r.n for r in language_model.gram_counts(language_model.trusted_texts(docs, labels)).collect()}
    assert sum(counts.values()) == 4099 * 5 + 30_000 and counts[int.from_bytes(b"zzzz", "big")] == 29_997
    fitted = language_model.train(docs, labels)
    grams = {r.gram for r in fitted.probs.where("ord = 4").collect()}
    assert len(grams) == len(counts)
