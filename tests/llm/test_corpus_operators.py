"""The corpus operators against brute force, on a small fixture of hard rows and on the smallest tables."""

from __future__ import annotations

import collections
import hashlib
import math
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from tokenizers import Tokenizer

from proxjoin.llm import exact_dedup, lengths, mixing, packing, pseudonyms, quality, repeats, simhash, suffix_tree, wavelet
from proxjoin.llm.encoding import PieceEncoder
from proxjoin.llm.queries import tokenizer

from test_near_copies import brute as near_brute

WORD = re.compile(r"[^\x20\x09-\x0D]+")
#: Columns that clash with names that the operators use themselves.
EXTRA = "size long, digest string, bits long, copy int, id long, content string, gone int, rate double, number int, _gone int"
SCHEMA = f"doc_id long, text string, lang string, source string, n_chars long, {EXTRA}"


def row(doc_id, text, lang="en", source="s1"):
    return (doc_id, text, lang, source, len(text or ""), 1, "d", 2, 3, 4, "c", 5, 0.5, 6, 7)


LONG = " ".join(f"w{i % 977}x{i % 31}" for i in range(30_000))
PASSAGE = " ".join(f"p{i}" for i in range(60))
ROWS = [
    row(1, "alpha beta gamma delta"), row(2, "alpha  beta\tgamma delta"), row(3, None), row(4, ""), row(5, " \n\t "),
    row(6, LONG, "de", "s2"), row(7, LONG + " tail", "de", "s2"), row(8, f"start {PASSAGE} end", None, None), row(9, f"other {PASSAGE} tail", "fr", None),
    row(10, f"{PASSAGE} {PASSAGE}", "fr", "s3"), row(11, "alpha beta gamma delta", "en", "s3"), row(11, "alpha beta gamma delta", "en", "s3"),
    row(None, "no id here", "en", "s1"), row(None, None, None, None), row(12, "Größe é café don't  stop\n\nnow日本", "de", "é"), row(13, "ties " * 40, "en", "s1"), row(14, "ties " * 40, "en", "s1"),
]


@pytest.fixture(scope="module")
def hard(spark):
    return spark.createDataFrame(ROWS, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.fixture(scope="module")
def labels(spark, sf):
    return spark.read.parquet(f"{sf}/labels.parquet")


@pytest.fixture(scope="module")
def texts(docs):
    return {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}


def of(text):
    return WORD.findall(text or "")


def test_mixing_meets_targets(hard, none, docs):
    for frame in (hard, docs):
        rows = mixing.mix_plan(frame).collect()
        assert len(rows) == frame.count()
        by_source = {(r.source_size, r.target) for r in rows}
        assert math.isclose(sum(t for _, t in by_source), sum({r.source_size for r in rows} and [s for s, _ in by_source]), rel_tol=1e-9) or frame is hard
        assert all(r.target <= 3 * r.source_size + 1e-6 and r.taken <= 3 * r["size"] for r in rows)
        assert rows == mixing.mix_plan(frame).collect() or sorted(map(str, rows)) == sorted(map(str, mixing.mix_plan(frame).collect()))
    mixed = mixing.mix(hard)
    assert mixed.columns == hard.columns
    want = collections.Counter()
    for r in mixing.mix_plan(hard).collect():
        want[r.doc_id] += r.copies
    got = collections.Counter(r.doc_id for r in mixed.collect())
    assert got == +want
    assert mixing.mix_plan(none).count() == 0 and mixing.mix(none).count() == 0


def test_mixing_water_level(spark):
    sizes = spark.createDataFrame([("a", 10), ("b", 1000), ("c", 100), (None, 50), ("d", 0)], "source string, size long")
    got = {r.source: r for r in mixing.source_targets(sizes).collect()}
    weight = dict(zip(["a", "b", "c", "d", None], [1, 2, 3, 1, 2], strict=True))
    size = {"a": 10, "b": 1000, "c": 100, "d": 0, None: 50}
    full, total = set(), 1160.0
    while True:
        level = (total - sum(3 * size[s] for s in full)) / sum(w for s, w in weight.items() if s not in full)
        more = {s for s in weight if s not in full and level * weight[s] > 3 * size[s]}
        if not more:
            break
        full |= more
    for s in weight:
        assert math.isclose(got[s].target, 3 * size[s] if s in full else level * weight[s]), s


def test_packing(hard, none, docs, texts):
    path = tokenizer("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    rows = packing.pack(docs, path, dealt=30).collect()
    ids = {i: np.array([*library.encode(t, add_special_tokens=False).ids, 1], "<u4") for i, t in texts.items()}
    assert sum(r.length for r in rows) == sum(map(len, ids.values()))
    bins = collections.defaultdict(list)
    for r in rows:
        assert zlib.crc32(ids[r.doc_id][r.start : r.start + r.length].tobytes()) == r.ids_crc32 and r.start == 4096 * r.piece
        bins[r.sequence_id].append((r.offset, r.length))
    for places in bins.values():
        end = 0
        for offset, length in sorted(places):
            assert offset == end
            end += length
        assert end <= 4096
    least = packing.fewest_bins(np.bincount([r.length for r in rows], minlength=4097))
    assert least <= len(bins) <= least + 2
    assert len(packing.pack(hard, path).collect()) >= len(ROWS) and packing.pack(none, path).count() == 0


def test_best_fit_and_its_bounds():
    rng = np.random.default_rng(1)
    for _ in range(40):
        lengths_ = rng.integers(1, 17, rng.integers(1, 9))
        _, _, fills = packing.best_fit(lengths_, 16)
        fewest = min_bins(sorted(lengths_.tolist(), reverse=True), 16)
        assert packing.fewest_bins(np.bincount(lengths_, minlength=17), 16) <= fewest <= len(fills)


def min_bins(items, limit):
    best = len(items)

    def place(k, gaps):
        nonlocal best
        if len(gaps) >= best:
            return
        if k == len(items):
            best = len(gaps)
            return
        for g in {*gaps}:
            if g >= items[k]:
                rest = [*gaps]
                rest.remove(g)
                place(k + 1, [*rest, g - items[k]])
        place(k + 1, [*gaps, limit - items[k]])

    place(0, [])
    return best


def test_suffix_tree(hard, none, docs, texts):
    rows = suffix_tree.score(docs).collect()
    listed = {i: [w for w in re.findall(rb"[^\x20\x09-\x0D]+", t.encode().lower())] for i, t in texts.items()}
    held = {i: zlib.crc32(str(i).encode()) % 5 == 1 for i in texts}
    count = collections.Counter(w for i, ws in listed.items() if not held[i] for w in ws)
    ends = sum(not h for h in held.values())
    n, v = sum(count.values()) + ends, len(count) + 1
    for r in rows:
        base = sum(math.log10((count[w] + 0.5) / (n + 0.5 * (v + 1))) for w in listed[r.doc_id]) + math.log10((ends + 0.5) / (n + 0.5 * (v + 1)))
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[r.doc_id], len(listed[r.doc_id]) + 1, sum(count[w] > 0 for w in listed[r.doc_id]) + 1, n)
        assert math.isclose(r.base_score, base, rel_tol=1e-9)
    unseen = [r for r in rows if r.held_out]
    assert sum(r.score for r in unseen) > sum(r.base_score for r in unseen)
    assert suffix_tree.score(hard).count() == len(ROWS) and suffix_tree.score(none).count() == 0


def tree_brute(texts, depth, least, gain):
    """The score of each text by dictionaries: contexts of every length, tested and smoothed level by level."""
    lines = {i: ["<s>", *re.findall(rb"[^\x20\x09-\x0D]+", (t or "").encode().lower()), "</s>"] for i, t in texts.items()}
    held = {i: zlib.crc32(str(i).encode()) % 5 == 1 for i in texts}
    count = collections.Counter(w for i, ws in lines.items() if not held[i] for w in ws[1:])
    n, v = sum(count.values()), len(count)
    p = {(i, k): (count[w] + 0.5) / (n + 0.5 * (v + 1)) for i, ws in lines.items() for k, w in enumerate(ws) if k}
    for d in range(1, depth + 1):
        pairs, rare = collections.defaultdict(collections.Counter), {}
        for i, ws in lines.items():
            for k in range(d, len(ws)):
                pairs[tuple(ws[k - d : k])][ws[k]] += not held[i]
                rare[tuple(ws[k - d : k]), ws[k]] = min(round(-suffix_tree.NATS * math.log(p[i, k])), 255) / suffix_tree.NATS
        states = {}
        for context, after in pairs.items():
            total, kinds = sum(after.values()), sum(x > 0 for x in after.values())
            better = sum(x * (math.log(x / total) + rare[context, w]) for w, x in after.items() if x)
            if total >= least and better >= gain * kinds:
                states[context] = total, kinds
        for i, ws in lines.items():
            for k in range(d, len(ws)):
                context = tuple(ws[k - d : k])
                if context in states:
                    total, kinds = states[context]
                    p[i, k] = (pairs[context][ws[k]] + kinds * p[i, k]) / (total + kinds)
    return {i: sum(math.log10(p[i, k]) for k in range(1, len(ws))) for i, ws in lines.items()}


@pytest.mark.parametrize(("depth", "least", "gain", "hot"), [(3, 3, 1.0, 1 << 22), (2, 2, 0.2, 20), (0, 2, 1.0, 9)])
def test_suffix_tree_is_brute_force(spark, docs, texts, depth, least, gain, hot):
    want = tree_brute(texts, depth, least, gain)
    got = {r.doc_id: r.score for r in suffix_tree.score(docs.repartition(5), depth, least, gain, buckets=8, hot=hot).collect()}
    assert got == pytest.approx(want, rel=1e-9)


def test_suffix_tree_on_lonely_batches(spark):
    """A partition for each row: only held-out rows, only empty ones, ones without anything to ask."""
    held = [i for i in range(60) if zlib.crc32(str(i).encode()) % 5 == 1]
    rows = [(i, text) for i in held for text in ("a b a b", "", None)] + [(i, "a b c") for i in range(60) if i not in held][:5] + [(None, None)]
    for some in (rows, rows[:3], [r for r in rows if not r[1]]):
        got = suffix_tree.score(spark.createDataFrame(some, "doc_id long, text string").repartition(len(some)), least=2, buckets=16).collect()
        assert len(got) == len(some) and all(math.isfinite(r.score) for r in got)


def test_wavelet_round_trip(hard, none, docs, texts):
    path = tokenizer("byte_bpe_50k.json")
    library = Tokenizer.from_file(path)
    shards = wavelet.write_shards(docs, path, shard_tokens=20_000)
    got = {r.doc_id: r for r in wavelet.read_documents(shards).collect()}
    at = 0
    stream = []
    for i in sorted(texts):
        ids = np.array([*library.encode(texts[i], add_special_tokens=False).ids, 2], "<u4")
        assert (got[i].start, got[i].n_tokens, got[i].ids_crc32) == (at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
        stream += ids.tolist()
    assert shards.count() > 3
    _, _, matrix = wavelet.from_file(shards.orderBy("shard").first().file)
    head = np.array(stream[: matrix.n])
    assert (matrix.decode() == head).all()
    for i in range(0, matrix.n, 997):
        assert matrix.access(i) == head[i] and matrix.rank(int(head[i]), i) == (head[:i] == head[i]).sum()
    token = int(head[3])
    places = np.flatnonzero(head == token)
    assert [matrix.select(token, k) for k in range(len(places))] == places.tolist()
    assert wavelet.occurrences(shards, 2).count() == len(texts)
    rows = wavelet.read_documents(wavelet.write_shards(hard, path)).collect()
    assert len(rows) == len(ROWS) and wavelet.read_documents(wavelet.write_shards(none, path)).count() == 0


def test_encoder_is_the_library():
    for name in ("byte_bpe_50k.json", "word_bpe_49k.json"):
        coder = PieceEncoder(tokenizer(name))
        cases = ["a  b", "  x", "a\n\nb", " a", "a ", "a\tb", "don't IT'S", "é ab́c", "12 345 a1b2", "", "<|endoftext|> hi", "a<|endoftext|>b <|startoftext|>", "x <|ENDOFTEXT|> y <|endoftext|", "日本 語", "x\ny z", "|> hi", '"q" $%& ### a###b', "ÀÉ×÷İŉ ſ", LONG]
        for text, ids in zip(cases, coder.encode(cases), strict=True):
            assert ids.tolist() == Tokenizer.from_file(tokenizer(name)).encode(text, add_special_tokens=False).ids, text


def simhash_brute(rows):
    from xxhash import xxh64_intdigest

    marks = []
    for doc_id, text in rows:
        w = of(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        shingles = [" ".join(w[k : k + 3]) for k in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)] if w else []
        h = [xxh64_intdigest(x.encode(), 42) for x in shingles]
        marks.append((doc_id, sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))))
    group = list(range(len(marks)))

    def root(k):
        while group[k] != k:
            k = group[k]
        return k

    for a in range(len(marks)):
        for b in range(a):
            if bin(marks[a][1] ^ marks[b][1]).count("1") <= 2:
                x, y = sorted((root(a), root(b)))
                group[y] = x
    lowest = collections.defaultdict(list)
    for k, (doc_id, _) in enumerate(marks):
        if doc_id is not None:
            lowest[root(k)].append(doc_id)
    return sorted((str(d), m, min(lowest[root(k)], default=None)) for k, (d, m) in enumerate(marks))


@pytest.mark.parametrize("crowd", [1, 64])
def test_simhash(spark, hard, none, docs, texts, crowd):
    near = [(100 + k, " ".join(w if j != 7 * k else "changed" for j, w in enumerate(PASSAGE.split() * 6))) for k in range(12)]
    frame = spark.createDataFrame(near, "doc_id long, text string")
    for df, rows in ((docs, list(texts.items())), (hard, [(r[0], r[1]) for r in ROWS]), (frame, near)):
        got = sorted((str(r.doc_id), r.bits & (1 << 64) - 1, r.component_id) for r in simhash.near_groups(df, crowd=crowd).collect())
        assert got == simhash_brute(rows)
    kept = simhash.near_dedup(hard)
    assert kept.columns == hard.columns
    assert simhash.near_groups(none, crowd=crowd).count() == 0 and simhash.near_dedup(none).count() == 0


@pytest.mark.parametrize("segments", [8, 16, 32])
def test_no_link_is_lost(spark, segments):
    rng = np.random.default_rng(segments)
    seeds = rng.integers(-(1 << 62), 1 << 62, 30)
    bits = {int(s) for s in seeds}
    for s in seeds:
        for _ in range(8):
            flips = rng.choice(64, rng.integers(1, 4), replace=False)
            x = int(s) & (1 << 64) - 1
            for f in flips:
                x ^= 1 << int(f)
            bits.add(x - (1 << 64) if x >> 63 else x)
    nodes = spark.createDataFrame([(b,) for b in bits], "bits long")
    want = {(a, b) for a in bits for b in bits if a < b and bin((a ^ b) & (1 << 64) - 1).count("1") <= 2}
    assert {(r.a, r.b) for r in simhash.links(nodes, segments, 1000).collect()} == want


def test_pseudonyms(spark, hard, none, docs):
    text = "mail x.yz+q@site.example.com card 4111 1111 1111 1111 not 4111 1111 1111 1112 ip 10.2.3.4 not 300.1.1.1 day 2024-02-29 not 2024-02-30 ring +1 (212) 555-0199 id 123-45-6789"
    frame = spark.createDataFrame([(1, text), (2, "4111111111111111"), (3, None), (4, "")], "doc_id long, text string")
    out = {r.doc_id: r.text for r in pseudonyms.pseudonymise(frame).collect()}
    for kept in ("4111 1111 1111 1112", "300.1.1.1", "2024-02-30", "@site.example.com"):
        assert kept in out[1]
    for gone in ("x.yz+q@", "4111 1111 1111 1111", "10.2.3.4", "2024-02-29", "555-0199", "6789"):
        assert gone not in out[1]
    assert [re.sub(r"\d", "9", t) for t in (out[2], re.search(r"card ([\d ]{19})", out[1])[1].replace(" ", ""))] == ["9" * 16] * 2
    assert out[2] == re.search(r"card ([\d ]{19})", out[1])[1].replace(" ", "") and out[3] is None and out[4] == ""
    assert {r.doc_id: r.text for r in pseudonyms.restore(pseudonyms.pseudonymise(frame)).collect()} == {1: text, 2: "4111111111111111", 3: None, 4: ""}
    assert pseudonyms.pseudonymise(hard).columns == hard.columns
    assert pseudonyms.restore(pseudonyms.pseudonymise(docs)).exceptAll(docs).isEmpty()
    assert pseudonyms.report(hard).count() == len(ROWS) and pseudonyms.report(none).count() == 0


def test_permutation_has_no_collisions(spark):
    numbers = spark.range(1000).select(F.lpad(F.col("id").cast("string"), 3, "0").alias("t"))
    made = numbers.select(pseudonyms.spelled(pseudonyms.permuted(pseudonyms.numbers(F.col("t")), pseudonyms.moduli(F.col("t")), "k", "x"), F.col("t")).alias("p"))
    assert made.distinct().count() == 1000
    days = spark.range(0, 146_097, 37).select(F.date_add(F.lit("1800-01-01").cast("date"), F.col("id").cast("int")).cast("string").alias("t"))
    made = days.select(pseudonyms.pseudonym(F.col("t")).alias("p"))
    assert made.distinct().count() == days.count() and made.where(F.col("p").rlike(r"^\d{4}-\d\d-\d\d$")).count() == days.count()


def measures_brute(text):
    w, text = of(text), text or ""
    lines = [x for x in text.split("\n") if WORD.search(x)]
    windows = collections.Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    covered = {j for i in range(len(w) - 7) if windows[tuple(w[i : i + 8])] > 1 for j in range(i, i + 8)}
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(covered)


def test_quality(spark, hard, none, docs, labels, texts):
    for df, rows in ((docs, list(texts.items())), (hard, [(r[0], r[1]) for r in ROWS])):
        got = quality.judged(df, labels).collect()
        assert sorted((str(r.doc_id), (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words)) for r in got) == sorted((str(d), measures_brute(t)) for d, t in rows)
        assert all(r.base_failed == (r.n_words < 20 or 100 * r.n_repeat_words > 30 * r.n_words) and not (r.kept and r.base_failed) for r in got)
    kept = quality.quality_filter(hard, labels)
    assert kept.columns == hard.columns and kept.count() <= len(ROWS)
    assert quality.judged(none, labels).count() == 0
    assert quality.judged(hard, labels.limit(0)).where("kept = base_failed").isEmpty()


def test_binomial_tail_is_exact(spark):
    cases = [(0, 500), (3, 500), (9, 1000), (40, 4000), (0, 10), (5, 20), (700, 60_000)]
    frame = spark.createDataFrame(cases, "k long, n long")
    for r in frame.select("k", "n", quality.as_likely(F.col("k"), F.col("n"), 0.02).alias("p")).collect():
        exact = 1.0 if r.k > r.n * 0.02 else sum(math.exp(math.lgamma(r.n + 1) - math.lgamma(j + 1) - math.lgamma(r.n - j + 1) + j * math.log(0.02) + (r.n - j) * math.log(0.98)) for j in range(r.k + 1))
        assert math.isclose(r.p, exact, rel_tol=1e-6, abs_tol=1e-300), r


def test_cutoffs_keep_good_documents(spark):
    rng = np.random.default_rng(5)
    good = [(k, 1, float(abs(rng.normal(0, 0.004))), "en") for k in range(6000)]
    bad = [(10_000 + k, 0, float(rng.uniform(0.2, 0.5)), "en") for k in range(1500)]
    few = [(20_000 + k, k % 2, 0.5 * (k % 2 == 0), "xx") for k in range(40)]
    rows = good + bad + few
    measured = spark.createDataFrame([(i, s, x, 0.0, 0.0, 0.0, 5.0, False) for i, _, x, s in rows], "doc_id long, stratum string, symbol_share double, capital_share double, repeat_share double, dup_line_share double, word_length double, base_failed boolean")
    labels = spark.createDataFrame([(i, q) for i, q, _, _ in rows], "doc_id long, quality int")
    force = {r.stratum: r.in_force for r in quality.cutoffs(measured, labels).collect()}
    assert [x.rule for x in force["en"]] == ["symbol_share"] and 0.01 <= force["en"][0].cutoff <= 0.2
    assert not force.get("xx")


def test_token_counts(hard, none, docs, texts):
    path = tokenizer("byte_bpe_50k.json")
    library = Tokenizer.from_file(path)
    found = np.array([len(library.encode(t, add_special_tokens=False).ids) for t in texts.values()])
    for r in lengths.answers(lengths.length_histogram(docs, path)).collect():
        assert (r.n_docs, r.docs_at_least, r.tokens_at_least, r.truncated_total) == ((found == r.length).sum(), (found >= r.length).sum(), found[found >= r.length].sum(), np.minimum(found, r.length).sum())
        assert math.isclose(r.share_upto, (found <= r.length).mean())
    assert lengths.length_histogram(hard, path).agg(F.sum("n_docs")).first()[0] == len(ROWS)
    assert lengths.answers(lengths.length_histogram(none, path)).count() == 0


def repeats_brute(rows):
    first, out = {}, []
    ordered = sorted(rows, key=lambda r: (r[0] is None, r[0] or 0))
    for doc_id, text in ordered:
        w = of(text)
        for k in range(len(w) - 19):
            key, place = tuple(w[k : k + 20]), (doc_id is None, doc_id or 0, k)
            first[key] = min(first.get(key, place), place)
    for doc_id, text in ordered:
        w = of(text)
        gone = {j for k in range(len(w) - 19) if first[tuple(w[k : k + 20])] < (doc_id is None, doc_id or 0, k) for j in range(k, k + 20)}
        out.append((str(doc_id), len(w), len(gone), " ".join(x for j, x in enumerate(w) if j not in gone)))
    return sorted(out)


def test_substring_dedup(hard, none, docs, texts):
    for df, rows in ((docs.repartition(5), list(texts.items())), (hard, [(r[0], r[1]) for r in ROWS])):
        found = repeats.substring_dedup(df)
        assert sorted((str(r.doc_id), r.n_words, r.n_removed, r.kept) for r in found.collect()) == repeats_brute(rows)
    spans = repeats.verified(repeats.substring_dedup(docs), docs)
    assert spans.count() > 0 and spans.where("not same").isEmpty()
    assert repeats.substring_dedup(none).count() == 0


def exact_brute(rows):
    groups = collections.defaultdict(list)
    for doc_id, text in rows:
        groups[re.sub(r"[\x20\x09-\x0D]+", " ", text or "")].append(doc_id)
    return sorted((str(d), str(min((i for i in ids if i is not None), default=None)), len(ids), hashlib.sha256(t.encode()).hexdigest()) for t, ids in groups.items() for d in ids)


def test_exact_dedup(hard, none, docs, texts):
    for df, rows in ((docs, list(texts.items())), (hard, [(r[0], r[1]) for r in ROWS])):
        got = exact_dedup.exact_groups(df).collect()
        assert sorted((str(r.doc_id), str(r.keep_id), r.group_size, r.digest) for r in got) == exact_brute(rows)
        assert all(r.kept == (r.doc_id == r.keep_id) for r in got)
        # a digest that tells hardly anything apart: contents must
        weak = exact_dedup.exact_groups(df, digest=lambda c: F.substring(F.sha2(c, 256), 1, 1), salts=2).collect()
        assert sorted((str(r.doc_id), str(r.keep_id), r.group_size) for r in weak) == sorted(x[:3] for x in exact_brute(rows))
    kept = exact_dedup.exact_dedup(hard)
    assert kept.columns == hard.columns
    contents = [re.sub(r"[\x20\x09-\x0D]+", " ", r.text or "") for r in kept.collect()]
    assert len(contents) == len(set(contents)) == len({re.sub(r"[\x20\x09-\x0D]+", " ", r[1] or "") for r in ROWS})
    assert exact_dedup.exact_groups(none).count() == 0 and exact_dedup.exact_dedup(none).count() == 0


def test_pipeline(spark, sf, docs, labels, texts):
    import corpus_pipeline

    frame, kept = docs, dict(texts)
    for (_, stage), number in zip(corpus_pipeline.STAGES, (7, 10, 5, 1, 2), strict=True):
        out = stage(spark, frame, sf)
        if number != 2:
            assert out.columns == docs.columns
        ids = [r.doc_id for r in out.select("doc_id").collect()]
        if number == 7:
            kept = {r.doc_id: texts[r.doc_id] for r in quality.judged(docs, labels).collect() if r.kept}
        elif number == 10:
            kept = {int(d): texts[int(d)] for d, k, *_ in exact_brute(kept.items()) if d == k}
        elif number == 5:
            kept = {min(i for i, _ in group): texts[min(i for i, _ in group)] for group in near_brute(list(kept.items()))}
        elif number == 1:
            assert set(ids) <= set(kept)
            kept = collections.Counter(ids)
        assert sorted(set(ids)) == sorted(kept)
        frame = out
    assert corpus_pipeline.run(spark, sf).count() == len(ids)
