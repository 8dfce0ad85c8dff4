"""Language-model scoring by a probabilistic suffix tree over the words of the corpus.

Each task lists the distinct words of its batches with their training counts;
these lists meet in buckets by hash and become the corpus vocabulary, which
numbers every word that training has. Texts travel as places in their batch's
list, and learn the numbers and counts of its words by a join.

The tree grows level by level, and is never in one place. A context of d words
is counted where it occurs LEAST times in training. Batches send each (context,
next word) once, with its count, to the bucket of the context; the bucket adds
up and answers. So the contexts, the next words kept and the buckets grow with
the corpus, and no count is dropped. A context that occurs HOT times is spread
over SALTS buckets by its next words, and its sums are added by who asked.

A context stays as a state if its next words differ enough from what its longest
suffix that stayed foretells: if the gain in likelihood, its count times the
divergence, is at least GAIN for each kind of next word. A state smooths its
counts into the suffix's by the number of kinds. A word is scored in the state of
its longest context; the root gives the base probability.

Defined cases: a null text is the empty text, whose one token is its end; a null
doc_id is the empty text for the dealing; rows that repeat a doc_id are scored
each, and learned from each; an empty table gives an empty result; without any
training text all counts are 0. Extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blobs import BASES, NULL, buckets_for, located, mixed, opened, rows, runs, squeezed, sub_batches
from .common import discarded, written

#: Longest context, times a context must occur in training, gain in nats for each kind of next word.
DEPTH, LEAST, GAIN = 3, 16, 1.0
#: Times that make a context hot, and the buckets that share one.
HOT, SALTS = 1 << 22, 64
#: Symbols of all batches that no text has, and the first number of a word; places of a batch's list start after two of them.
END, START, UNKNOWN, FIRST = range(4)
FOLDS, HELD_OUT = 5, 1
#: Bytes of text in one batch and in one bucket; steps of a nat by which improbability is sent for the divergence test.
STEP, EACH, NATS = 6 << 20, 16 << 20, 8
BATCH = [("batch", pa.int64()), ("bucket", pa.int64()), ("held", pa.bool_()), ("data", pa.binary())]
PLACED = [("batch", pa.int64()), ("data", pa.binary())]
SENT = [("bucket", pa.int64()), ("batch", pa.int64()), ("data", pa.binary())]
SENT_SQL = "bucket long, batch long, data binary"
SCORES = [("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64())]
SCORES_SQL = "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double"


def held_out(doc_id: int) -> bool:
    return zlib.crc32(b"" if doc_id == NULL else str(doc_id).encode()) % FOLDS == HELD_OUT


def word_lists(docs: DataFrame, buckets: int) -> DataFrame:
    """Written once: for each batch its texts as places in its list of words, and that list by buckets with training counts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 32
        for batch in batches:
            for ids, texts in sub_batches(batch, STEP):
                raws = [(t or "").encode().lower() for t in texts]
                raw, at, stop, key, sizes = located(raws)
                held = np.array([held_out(i) for i in ids.tolist()], bool)
                distinct, sample, which = np.unique(key, return_index=True, return_inverse=True)
                counts = np.bincount(which, weights=np.repeat(~held, sizes), minlength=len(distinct)).astype("<u4")
                bucket = (distinct % np.uint64(buckets)).astype(np.int64)
                order = np.argsort(bucket, kind="stable")
                place = np.empty(len(order), "<u4")
                place[order] = np.arange(len(order), dtype="<u4")
                out = [(number, -1, False, squeezed(ids, held.astype("u1"), sizes.astype("<u4"), place[which]))]
                for a, b in runs(bucket[order]):
                    some = order[a:b]
                    words = [raw[x:y] for x, y in zip(at[sample[some]].tolist(), stop[sample[some]].tolist(), strict=True)]
                    out.append((number, int(bucket[some[0]]), False, listed_packed(words, counts[some])))
                number += 1
                yield from rows(BATCH, *map(list, zip(*out, strict=True))).to_batches()

    return written(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "batch long, bucket long, held boolean, data binary").drop("held"), "words", "uncompressed")


def listed_packed(words: list[bytes], counts: np.ndarray) -> bytes:
    body = zstandard.ZstdCompressor(level=1).compress(b" ".join(words))
    return len(body).to_bytes(4, "little") + body + squeezed(counts)


def listed_opened(data: bytes) -> tuple[list[bytes], np.ndarray]:
    size = int.from_bytes(data[:4], "little")
    return zstandard.ZstdDecompressor().decompress(data[4 : 4 + size]).split(b" "), opened(data[4 + size :])[0]


def vocabulary(lists: DataFrame) -> DataFrame:
    """bucket, tokens, kinds, data: the words of the corpus with their training counts, one row for each bucket."""

    def merge(table: pa.Table) -> pa.Table:
        total: dict[bytes, int] = {}
        for data in table.column("data"):
            words, counts = listed_opened(data.as_py())
            for word, n in zip(words, counts.tolist(), strict=True):
                total[word] = total.get(word, 0) + n
        counts = np.fromiter(total.values(), "<i8", len(total))
        order = np.argsort(-counts, kind="stable")  # frequent words get small numbers, which pack better
        words, counts = list(total), counts[order]
        words = [words[k] for k in order.tolist()]
        return rows([("bucket", pa.int64()), ("tokens", pa.int64()), ("kinds", pa.int64()), ("data", pa.binary())], [table.column("bucket")[0].as_py()], [int(counts.sum())], [int((counts > 0).sum())], [listed_packed(words, counts)])

    return written(lists.where("bucket >= 0").select("bucket", "data").groupBy("bucket").applyInArrow(merge, "bucket long, tokens long, kinds long, data binary"), "vocabulary", "uncompressed")


def word_numbers(lists: DataFrame, known: DataFrame, buckets: int) -> DataFrame:
    """batch, bucket, data: the training count and the number of each word of a batch's list, in its order."""

    def answer(asked: pa.Table, corpus: pa.Table) -> pa.Table:
        words, counts = listed_opened(corpus.column("data")[0].as_py())
        number = np.where(counts > 0, FIRST + np.arange(len(words)) * buckets + corpus.column("bucket")[0].as_py(), UNKNOWN)
        place = {w: k for k, w in enumerate(words)}
        out = []
        for data in asked.column("data"):
            some, _ = listed_opened(data.as_py())
            at = np.fromiter(map(place.__getitem__, some), np.int64, len(some))
            out.append(squeezed(counts[at], number[at].astype("<u8")))
        return rows([("batch", pa.int64()), ("bucket", pa.int64()), ("data", pa.binary())], asked.column("batch").to_pylist(), asked.column("bucket").to_pylist(), out)

    return lists.where("bucket >= 0").groupBy("bucket").cogroup(known.select("bucket", "data").groupBy("bucket")).applyInArrow(answer, "batch long, bucket long, data binary")


def in_order(buckets: pa.ChunkedArray, data: pa.ChunkedArray) -> list[list[np.ndarray]]:
    """The arrays of each bucket, by ascending bucket; opened one by one."""
    order = np.argsort(buckets.to_numpy(), kind="stable").tolist()
    return [opened(data[k].as_py()) for k in order]


def joined(parts: list[list[np.ndarray]], kinds: tuple[type, ...]) -> list[np.ndarray]:
    return [np.concatenate([p[k] for p in parts]) if parts else np.zeros(0, kind) for k, kind in enumerate(kinds)]


def symbolised(lists: DataFrame, numbers: DataFrame) -> DataFrame:
    """batch, data: the texts of a batch as places in its list, and the counts and numbers of that list's words."""

    def place(batch: pa.Table, words: pa.Table) -> pa.Table:
        own = opened(batch.column("data")[0].as_py())
        counts, number = joined(in_order(words.column("bucket"), words.column("data")), (np.int64, np.uint64))
        return rows(PLACED, [batch.column("batch")[0].as_py()], [squeezed(*own, counts.astype("<u8"), number.astype("<u8"))])

    met = lists.where("bucket < 0").select("batch", "data").groupBy("batch").cogroup(numbers.groupBy("batch"))
    return written(met.applyInArrow(place, "batch long, data binary"), "symbols", "uncompressed")


def grouped(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The distinct keys in ascending order, a place of each, and which of them each key is."""
    order = np.argsort(keys)
    ascending = keys[order]
    new = np.diff(ascending, prepend=~ascending[:1]) != 0
    which = np.empty(len(keys), np.int64)
    which[order] = np.cumsum(new) - 1
    return ascending[new], order[new], which


def both(high: np.ndarray, low: np.ndarray) -> np.ndarray:
    return high.astype(np.uint64) << np.uint64(32) | low.astype(np.uint64)


class Walk:
    """The texts of one batch on their way down the tree: for each symbol its probability so far and its context of the level.

    ``meet`` puts the distinct (context, next) of the level in an order that the
    data alone decide, so that the answers, in that order, are all ``step`` needs.
    """

    def __init__(self, data: bytes, n: int, v: int, ends: int, least: int = LEAST, gain: float = GAIN, hot: int = HOT):
        self.ids, self.held, sizes, place, counts, numbers = opened(data)
        self.sizes = sizes.astype(np.int64)
        stops = np.cumsum(self.sizes)
        self.first = stops - self.sizes + 2 * np.arange(len(sizes))  # where each text's START stands
        self.text = np.zeros(len(place) + 2 * len(sizes), np.int32)
        self.text[self.first] = START
        self.text[np.arange(len(place)) + np.repeat(2 * np.arange(len(sizes)) + 1, sizes)] = place.astype(np.int32) + 2
        self.numbers = np.r_[np.array([END, START], np.uint64), numbers.astype(np.uint64)]
        self.place = np.argsort(np.argsort(self.numbers, kind="stable"))
        self.counts = np.r_[ends, ends, counts.astype(np.int64)]
        self.base = (self.counts + 0.5) / (n + 0.5 * (v + 1))
        self.p = self.base[self.text]
        self.p[self.first] = 1.0
        self.train = np.repeat(self.held == 0, self.sizes + 2)
        self.least, self.gain, self.hot = least, gain, hot
        self.name, self.total = mixed(self.numbers), np.r_[0, ends, counts.astype(np.int64)]
        before = np.r_[np.int32(END), self.text[:-1]]
        self.context = np.where(self.total[before] >= least, before, -1)
        self.context[self.first] = -1

    def meet(self, buckets: int) -> None:
        """The pairs of the level, and the parts of contexts that they are asked under."""
        self.at = np.flatnonzero(self.context >= 0)
        pair, self.sample, self.which = grouped(both(self.context[self.at], self.text[self.at]))
        self.of, after = (pair >> np.uint64(32)).astype(np.int64), (pair & np.uint64(0xFFFFFFFF)).astype(np.int64)
        self.next = self.numbers[after]
        many = self.total[self.of] >= self.hot
        salt = np.where(many, (mixed(self.next) % np.uint64(SALTS)).astype(np.int64), 0)
        part = self.of * SALTS + salt
        whole = (np.unique(self.of[many])[:, None] * SALTS + np.arange(SALTS)).ravel()  # sums of a hot context come from all that share it
        parts = np.union1d(part, whole)
        names = mixed(self.name[parts // SALTS] + (parts % SALTS).astype(np.uint64) * np.uint64(BASES[1]))
        bucket = (names % np.uint64(buckets)).astype(np.int64)
        rank = np.lexsort((names, bucket))
        back = np.empty(len(rank), np.int64)
        back[rank] = np.arange(len(rank))
        mine = back[np.searchsorted(parts, part)]
        self.order = np.argsort(both(mine, self.place[after]))
        self.size = np.bincount(mine, minlength=len(parts))
        self.parts, self.names, self.bucket = parts[rank] // SALTS, names[rank], bucket[rank]

    def asked(self) -> Iterator[tuple[int, bytes]]:
        """For each bucket its contexts, and the next words of each with their counts here and how improbable they are so far."""
        n = np.bincount(self.which, weights=self.train[self.at], minlength=len(self.of))[self.order].astype("<u4")
        rare = np.minimum(np.rint(-NATS * np.log(self.p[self.at[self.sample[self.order]]])), 255).astype("u1")
        start = np.r_[0, np.cumsum(self.size)]
        after = self.next[self.order]
        step = np.diff(after, prepend=np.uint64(0))
        own = start[:-1][self.size > 0]
        step[own] = after[own]
        for a, b in runs(self.bucket):
            x, y = start[a], start[b]
            yield int(self.bucket[a]), squeezed(np.diff(self.names[a:b], prepend=np.uint64(0)), self.size[a:b].astype("<u4"), step[x:y], n[x:y], rare[x:y])

    def step(self, kinds: np.ndarray, gain: np.ndarray, counts: np.ndarray) -> None:
        """Takes the answers: of each part its sums, of each pair its count; then the contexts are one word longer."""
        total = self.total  # something follows wherever a context ends in training
        kinds, gain = (np.bincount(self.parts, weights=x.astype(float), minlength=len(total)) for x in (kinds, gain))
        stays = (kinds > 0) & (gain - total * np.log(np.maximum(total, 1)) >= self.gain * kinds)
        pairs = np.empty(len(self.order), np.int64)
        pairs[self.order] = counts.astype(np.int64)
        known = stays[self.of][self.which]
        at, which = self.at[known], self.which[known]
        of = self.of[which]
        self.p[at] = (pairs[which] + kinds[of] * self.p[at]) / (total + kinds)[of]
        longer = np.full(len(self.text), -1, np.int64)
        longer[self.at] = np.where(pairs[self.which] >= self.least, self.which, -1)
        self.context = np.r_[-1, longer[:-1]]
        self.context[self.first] = -1
        self.name, self.total = mixed(self.name[self.of] * np.uint64(BASES[0]) + mixed(self.next)), pairs

    def scores(self) -> pa.Table:
        def sums(values: np.ndarray) -> np.ndarray:
            values[self.first] = 0.0
            return np.add.reduceat(values, self.first) if len(self.first) else np.zeros(0)

        known = sums((self.counts > 0)[self.text].astype(float)).astype(np.int64)
        return rows(SCORES, [None if i == NULL else i for i in self.ids.tolist()], self.held.astype(bool), self.sizes + 1, known, sums(np.log10(self.base)[self.text]), sums(np.log10(self.p)))


def merged(table: pa.Table) -> pa.Table:
    """The answers of one bucket to each batch: the sums of the contexts it asked for, and the count of each pair."""
    names, afters, counts, rare, sizes, places, first = [], [], [], [], [], [], 0
    for data in table.column("data"):
        name, size, step, n, r = opened(data.as_py())
        total = np.cumsum(step, dtype=np.uint64)
        begin = np.cumsum(size, dtype=np.int64) - size
        before = np.where(begin > 0, total[np.maximum(begin, 1) - 1], np.uint64(0)) if len(total) else np.zeros(len(begin), np.uint64)
        names.append(np.cumsum(name, dtype=np.uint64))
        afters.append(total - np.repeat(before, size))
        places.append(np.repeat(np.arange(first, first + len(name)), size))
        counts.append(n)
        rare.append(r)
        sizes.append((len(name), len(n)))
        first += len(name)
    kinds, _, part = grouped(np.concatenate(names))
    after = grouped(np.concatenate(afters))[2]
    del names, afters
    pair, sample, which = grouped(both(part[np.concatenate(places)], after))
    del after, places
    n = np.bincount(which, weights=np.concatenate(counts), minlength=len(pair))
    of = (pair >> np.uint64(32)).astype(np.int64)
    gain = n * (np.log(np.maximum(n, 1)) + np.concatenate(rare)[sample] / NATS)
    several, gain = (np.bincount(of, weights=w, minlength=len(kinds)) for w in (n > 0, gain))
    out, a, x = [], 0, 0
    for parts, pairs in sizes:
        mine = part[a : a + parts]
        out.append(squeezed(several[mine].astype("<u4"), gain[mine].astype("<f4"), n[which[x : x + pairs]].astype("<u8")))
        a, x = a + parts, x + pairs
    return rows(SENT, table.column("bucket").to_pylist(), table.column("batch").to_pylist(), out)


def score(docs: DataFrame, depth: int = DEPTH, least: int = LEAST, gain: float = GAIN, buckets: int | None = None, hot: int = HOT) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score of every document."""
    buckets = buckets or buckets_for(docs, EACH)
    lists = word_lists(docs, buckets)
    known = vocabulary(lists)
    doc_id = F.coalesce(F.col("doc_id").cast("string"), F.lit(""))
    ends = docs.where(F.crc32(doc_id) % FOLDS != HELD_OUT).count()
    tokens, kinds = known.agg(F.coalesce(F.sum("tokens"), F.lit(0)), F.coalesce(F.sum("kinds"), F.lit(0))).first()
    n, v = tokens + ends, kinds + (ends > 0)
    texts = symbolised(lists, word_numbers(lists, known, buckets))
    discarded(lists, known)

    def walked(data: bytes, answers: pa.Table | None) -> Walk:
        """The batch after all levels that have been answered."""
        walk = Walk(data, n, v, ends, least, gain, hot)
        levels = answers.column("level").to_numpy() if answers is not None else np.zeros(0, np.int64)
        for d in range(1, int(levels.max(initial=0)) + 1):
            walk.meet(buckets)
            some = answers.filter(pa.array(levels == d))
            walk.step(*joined(in_order(some.column("bucket"), some.column("data")), (np.uint32, np.float32, np.uint64)))
        return walk

    def asked(walk: Walk, batch: int) -> pa.Table:
        walk.meet(buckets)
        sent = list(walk.asked())
        return rows(SENT, [b for b, _ in sent], [batch] * len(sent), [d for _, d in sent])

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for some in batches:
            for batch, data in zip(some.column(0).to_pylist(), some.column(1), strict=True):
                yield from asked(walked(data.as_py(), None), batch).to_batches()

    def later(own: pa.Table, answers: pa.Table) -> pa.Table:
        return asked(walked(own.column("data")[0].as_py(), answers), own.column("batch")[0].as_py())

    def last(own: pa.Table, answers: pa.Table) -> pa.Table:
        return walked(own.column("data")[0].as_py(), answers).scores()

    answers: DataFrame | None = None
    for d in range(1, depth + 1):
        asks = texts.mapInArrow(first, SENT_SQL) if answers is None else texts.groupBy("batch").cogroup(answers.groupBy("batch")).applyInArrow(later, SENT_SQL)
        level = written(asks.repartition(buckets, "bucket").groupBy("bucket").applyInArrow(merged, SENT_SQL), "level", "uncompressed").withColumn("level", F.lit(d))
        answers = level if answers is None else answers.union(level)
    if answers is None:
        scored = texts.groupBy("batch").applyInArrow(lambda own: last(own, None), SCORES_SQL)
    else:
        scored = texts.groupBy("batch").cogroup(answers.groupBy("batch")).applyInArrow(last, SCORES_SQL)
    return scored.withColumn("train_tokens", F.lit(n).cast("long"))
