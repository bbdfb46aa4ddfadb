"""Hidden Markov language model over words.

Every word is observed through a class: the most frequent ``words`` words are a class each, all other words fall into
one of ``kinds`` classes by their last two characters, and the text's end is a class. P(word | state) is
P(class | state) times P(word | class), the latter from the smoothed counts of all training words; so the model has a
fixed size while the counts grow with the corpus.

1. One pass over the texts cuts them into blocks and writes, per block, the distinct words with their training counts
   and the texts as places in that list.
2. Counts are summed per word over all blocks and joined back to the blocks' lists, not to single occurrences.
3. Per block, each text gets its unigram score and the sequence of its classes.
4. Baum-Welch: the start model comes from a bounded sample (``SEED_DOCS`` whole texts); then every round adds up the
   expected counts of all training texts per partition and over partitions. Each whole text is one sequence; one longer
   than ``LONG`` is walked in pieces, with the exact forward and backward vectors at the cuts.
5. The scaled forward recursion over each whole text gives its exact log likelihood.

Defined results: a null text is the empty text, whose one token is the end; texts of any length are read whole;
repeated rows count and are scored each; with no training rows the base score is that of the empty model and ``score``
that of the start model.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import Stored
from .common import hand_back, steady, text_rows

STATES = 8
WORDS = 8192
KINDS = 512
SMOOTH = 0.1
#: Bytes of text in a block.
BLOCK_BYTES = 16 << 20
#: Longer sequences are walked in pieces, with the exact vectors at the cuts.
LONG, PIECE = 2048, 512
#: Whole texts that the start model is fitted on, at most.
SEED_DOCS = 600
SEED_ROUNDS = 12
#: Rounds over all training texts, fewer where one gains less than this share of the log likelihood.
ROUNDS, SETTLED = 6, 5e-4
#: Pseudo-count of a state's classes, in shares of the corpus.
PRIOR = 20.0
#: Tokens in one batch of the recursions, and tokens of texts gathered to be put into batches by length.
BATCH_TOKENS, POOL_TOKENS = 250_000, 3_000_000
#: Steps between two scalings of the forward vectors.
SCALED = 4
END = "\n"  # no word holds a line break


@dataclass
class Model:
    start: np.ndarray
    step: np.ndarray
    emit: np.ndarray  # class x state


class Places(dict):
    """Numbers words in the order they are met."""

    def __missing__(self, word: bytes) -> int:
        n = self[word] = len(self)
        return n


def blocks(docs: DataFrame) -> DataFrame:
    """Rows of two kinds from (doc_id, held_out, text): a block's words (word, at, n) and its texts (doc_id, held_out, ids)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base, seq = TaskContext.get().partitionId() << 24, 0
        press = zstandard.ZstdCompressor(level=1).compress
        place, trained, size = Places(), np.zeros(1 << 16, np.int64), 0

        def words() -> Iterator[pa.RecordBatch]:
            every = list(place)
            for lo in range(0, len(every), 100_000):
                part = every[lo : lo + 100_000]
                n = len(part)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(n, base + seq)), pa.array(part, pa.binary()).cast(pa.string()), pa.array(np.arange(lo, lo + n)), pa.array(trained[lo : lo + n]), pa.nulls(n, pa.int64()), pa.nulls(n, pa.bool_()), pa.nulls(n, pa.binary())],
                    ["block", "word", "at", "n", "doc_id", "held_out", "ids"],
                )

        for batch, texts in text_rows(batches):
            out, held = [], batch.column(1).to_pylist()
            lo = 0
            for i, text in enumerate(texts):
                tokens = text.lower().split() if text else []
                tokens.append(b"\n")
                ids = np.fromiter(map(place.__getitem__, tokens), np.uint32, len(tokens))
                if len(place) > len(trained):
                    trained = np.concatenate((trained, np.zeros(len(place), np.int64)))
                if not held[i]:
                    np.add.at(trained, ids, 1)
                out.append(press(ids.tobytes()))
                size += len(text or b"") + 1
                if size >= BLOCK_BYTES or i == len(texts) - 1:
                    n = i + 1 - lo
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(n, base + seq)), pa.nulls(n, pa.string()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.int64()), batch.column(0).slice(lo, n), batch.column(1).slice(lo, n), pa.array(out, pa.binary())], ["block", "word", "at", "n", "doc_id", "held_out", "ids"])
                    out, lo = [], i + 1
                if size >= BLOCK_BYTES:
                    yield from words()
                    place, trained, size, seq = Places(), np.zeros(1 << 16, np.int64), 0, seq + 1
        if place:
            yield from words()
        place.clear()
        hand_back()

    return docs.select("doc_id", "held_out", "text").mapInArrow(run, "block long, word string, at long, n long, doc_id long, held_out boolean, ids binary")


def packed(seqs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Sequences laid out step by step, the longest first: (order, lengths, live per step, place of each step, classes)."""
    lengths = np.array([len(x) for x in seqs])
    order = np.argsort(-lengths, kind="stable")
    lengths = lengths[order]
    live = np.searchsorted(-lengths, -np.arange(lengths[0]), side="left")
    first = np.concatenate(([0], np.cumsum(live)))
    flat = np.empty(first[-1], np.int32)
    for i, j in enumerate(order.tolist()):
        flat[first[: lengths[i]] + i] = seqs[j]
    return order, lengths, live, first, flat


def by_state(model: Model, kind: type) -> tuple[np.ndarray, np.ndarray]:
    """Each class's emission over the states (class x state) with rows that sum to 1, and the sums' log10."""
    total = model.emit.sum(1)
    return np.ascontiguousarray((model.emit / total[:, None]).astype(kind)), np.log10(total)


def ahead(step: np.ndarray, seen: np.ndarray, live: np.ndarray, first: np.ndarray, entry: np.ndarray, shares: np.ndarray | None) -> tuple[np.ndarray, dict[int, np.ndarray]]:
    """Forward recursion from the predictions ``entry`` (sequence x state): log10 of each sequence's mass, and the scales.

    It is scaled to 1 at every ``SCALED`` steps. ``shares`` gets the scaled vectors at all places, if given.
    """
    ones, logs, scales = np.ones(len(step), step.dtype), np.zeros(len(entry)), {}
    a, n_steps = entry, len(live)
    for t in range(n_steps):
        k, lo, hi = live[t], first[t], first[t + 1]
        a = a[:k] if t == 0 else np.matmul(a[:k], step)
        a = np.multiply(a, seen[lo:hi], out=None if shares is None else shares[lo:hi])
        if t % SCALED == 0:
            n = np.matmul(a, ones)
            a /= n[:, None]
            logs[:k] += np.log10(n)
            if shares is not None:
                scales[t] = n[:, None]
        stay = live[t + 1] if t + 1 < n_steps else 0
        if stay < k:
            logs[stay:k] += np.log10(np.matmul(a[stay:], ones))
    return logs, scales


def cut_points(model: Model, seqs: list[np.ndarray], piece: int) -> tuple[list[np.ndarray], np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Long sequences in pieces: (pieces, each one's sequence, shares of states before it, predictions at its start, weights after it).

    All pieces are walked together from every state, which gives each one's matrix of passage; the matrices in turn
    give the exact forward and backward vectors at the cuts.
    """
    s = len(model.start)
    parts = [x[lo : lo + piece] for x in seqs for lo in range(0, len(x), piece)]
    owner = np.repeat(np.arange(len(seqs)), [-(-len(x) // piece) for x in seqs])
    opens = np.concatenate(([True], owner[1:] != owner[:-1]))
    order, _, live, first, flat = packed(parts)
    seen = np.ascontiguousarray(by_state(model, float)[0][flat].T)
    through = np.empty((s, s, len(parts)))  # to, from, piece
    through[:] = np.where(opens[order], np.eye(s)[:, :, None], model.step.T[:, :, None]) * seen[:, None, : live[0]]
    for t in range(1, len(live)):
        m = live[t]
        x = (model.step.T @ through[:, :, :m].reshape(s, -1)).reshape(s, s, m) * seen[:, None, first[t] : first[t + 1]]
        through[:, :, :m] = x / x.sum((0, 1)) if t % 16 == 0 else x
    passage = np.empty((len(parts), s, s))
    passage[order] = through.transpose(2, 0, 1)
    before, after = np.tile(model.start, (len(parts), 1)), np.ones((len(parts), s))
    for i in range(len(parts) - 1):
        if not opens[i + 1]:
            a = passage[i] @ before[i]
            before[i + 1] = a / a.sum()
    for i in range(len(parts) - 1, 0, -1):
        if not opens[i]:
            b = after[i] @ passage[i]
            after[i - 1] = b / b.sum()
    entry = np.where(opens[:, None], model.start, before @ model.step)
    return parts, owner, before, entry, after


def grouped(seqs: list[np.ndarray], most: int) -> Iterator[list[int]]:
    """Places of the sequences, the longest first, in runs of about so many tokens: a run's lengths are alike."""
    part, n = [], 0
    for i in sorted(range(len(seqs)), key=lambda i: -len(seqs[i])):
        part.append(i)
        n += len(seqs[i])
        if n >= most:
            yield part
            part, n = [], 0
    if part:
        yield part


def forward(model: Model, seqs: list[np.ndarray]) -> np.ndarray:
    """log10 likelihood of each whole sequence; sequences alike in length step together, a long one's pieces too."""
    emit, outer = by_state(model, float)
    total = np.array([outer[x].sum() for x in seqs])

    def add(parts: list[np.ndarray], entry: np.ndarray, owner: np.ndarray) -> None:
        order, _, live, first, flat = packed(parts)
        np.add.at(total, owner[order], ahead(model.step, emit[flat], live, first, entry[order], None)[0])

    for part in grouped(seqs, BATCH_TOKENS):
        whole = [i for i in part if len(seqs[i]) <= LONG]
        if whole:
            add([seqs[i] for i in whole], np.tile(model.start, (len(whole), 1)), np.array(whole))
        long = [i for i in part if len(seqs[i]) > LONG]
        if long:
            parts, owner, _, entry, _ = cut_points(model, [seqs[i] for i in long], PIECE)
            for some in grouped(parts, BATCH_TOKENS):
                add([parts[j] for j in some], entry[some], np.array(long)[owner[some]])
    return total


def expect(model: Model, seqs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """Expected starts, steps and emissions of whole sequences, and their log10 likelihood."""
    s, c = len(model.start), len(model.emit)
    step, (emit, outer) = model.step.astype(np.float32), by_state(model, np.float32)
    back = np.ascontiguousarray(step.T)
    starts, steps, emits, fit = np.zeros(s), np.zeros((s, s)), np.zeros((s, c)), 0.0

    def add(parts: list[np.ndarray], opens: np.ndarray, before: np.ndarray, entry: np.ndarray, after: np.ndarray) -> None:
        nonlocal starts, steps, fit
        order, lengths, live, first, flat = packed(parts)
        seen = emit[flat]
        shares, later = np.empty_like(seen), np.empty_like(seen)
        logs, scales = ahead(step, seen, live, first, entry[order].astype(np.float32), shares)
        ends = first[lengths - 1] + np.arange(len(order))
        b = after[order]
        later[ends] = b / (shares[ends] * b).sum(1, keepdims=True)
        for t in range(len(live) - 1, -1, -1):  # seen becomes what a state passes back
            lo, hi = first[t], first[t + 1]
            e = np.multiply(seen[lo:hi], later[lo:hi], out=seen[lo:hi])
            if t in scales:
                e /= scales[t]
            if t:
                np.matmul(e, back, out=later[first[t - 1] : first[t - 1] + hi - lo])
        moves, prev = np.zeros((s, s)), np.arange(live[0], len(flat)) - np.repeat(live[:-1], live[1:])
        for lo in range(0, len(prev), 1 << 16):
            moves += shares[prev[lo : lo + (1 << 16)]].T @ seen[live[0] + lo : live[0] + lo + (1 << 16)]
        opened = opens[order]
        moves += before[order[~opened]].T @ seen[: live[0]][~opened]
        steps += moves * model.step
        shares *= later
        shares /= np.matmul(shares, np.ones(s, np.float32))[:, None]
        starts += shares[: live[0]][opened].sum(0, dtype=float)
        for i in range(s):
            emits[i] += np.bincount(flat, weights=shares[:, i], minlength=c)
        fit += float(logs.sum() + outer[flat].sum())

    for part in grouped(seqs, BATCH_TOKENS):
        whole = [seqs[i] for i in part if len(seqs[i]) <= LONG]
        if whole:
            n, entry = len(whole), np.tile(model.start, (len(whole), 1))
            add(whole, np.ones(n, bool), entry, entry, np.ones((n, s)))
        long = [seqs[i] for i in part if len(seqs[i]) > LONG]
        if long:
            parts, owner, before, entry, after = cut_points(model, long, PIECE)
            opens = np.concatenate(([True], owner[1:] != owner[:-1]))
            for some in grouped(parts, BATCH_TOKENS):
                add([parts[j] for j in some], opens[some], before[some], entry[some], after[some])
    return starts, steps, emits.T, fit


def improved(counts: tuple[np.ndarray, np.ndarray, np.ndarray], share: np.ndarray) -> Model:
    start, step, emit = counts[0] + 0.1, counts[1] + 0.1, counts[2] + PRIOR * share[:, None]
    return Model(start / start.sum(), step / step.sum(1, keepdims=True), emit / emit.sum(0))


def seeded(sample: list[np.ndarray], share: np.ndarray, states: int, seed: int = 7) -> Model:
    """A start model: sticky states, each leaning towards some sample texts, bettered on the sample alone."""
    rng = np.random.default_rng(seed)
    c = len(share)
    emit = np.tile(share[:, None], (1, states))
    chosen = rng.permutation(len(sample))[: 4 * states]
    for j, i in enumerate(chosen):
        emit[:, j % states] += 0.5 * np.bincount(sample[i], minlength=c) / len(sample[i])
    step = np.full((states, states), 0.05 / max(states - 1, 1))
    np.fill_diagonal(step, 0.95)
    model = Model(np.full(states, 1 / states), step / step.sum(1, keepdims=True), emit / emit.sum(0))
    for _ in range(SEED_ROUNDS if sample else 0):
        model = improved(expect(model, sample)[:3], share)
    return model


def unpack(data: bytes) -> np.ndarray:
    return np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint16)


def pooled(batches: Iterator[pa.RecordBatch], column: int, most: int = POOL_TOKENS) -> Iterator[list[np.ndarray]]:
    """The sequences of a column of compressed classes, so many tokens together."""
    part, n = [], 0
    for batch in batches:
        for x in batch.column(column):
            part.append(unpack(x.as_buffer()))
            n += len(part[-1])
            if n >= most:
                yield part
                part, n = [], 0
    if part:
        yield part


class Trained:
    """Counts, encoded texts and the fitted model of one corpus."""

    def __init__(self, docs: DataFrame, states: int = STATES, words: int = WORDS, kinds: int = KINDS, rounds: int = ROUNDS):
        """``docs``: (doc_id, held_out, text)."""
        spark = docs.sparkSession
        steady(spark)
        self.classes = words + kinds + 1
        cut_up = Stored(blocks(docs), "lm-blocks")
        vocab = cut_up.df.where("word is not null").select("block", "word", "at", "n")
        counts = Stored(vocab.groupBy("word").agg(F.sum("n").alias("c")).where("c > 0"), "lm-counts")
        kind = (F.lit(words) + F.pmod(F.xxhash64(F.substring("word", -2, 2)), F.lit(kinds))).cast("int")
        self.tokens, self.distinct = (counts.df.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*"))).first()
        top = counts.df.where(F.col("word") != END).orderBy(F.desc("c"), "word").limit(words).collect()  # bounded by the model's size
        head = spark.createDataFrame([(r.word, i) for i, r in enumerate(top)], "word string, own int")
        # The most frequent words and the end, which most blocks hold, go by broadcast (the model's size); only the others are shuffled.
        classed = counts.df.join(F.broadcast(head), "word", "left").select("word", "c", F.when(F.col("word") == END, self.classes - 1).otherwise(F.coalesce("own", kind)).alias("cls"), (F.col("own").isNotNull() | (F.col("word") == END)).alias("frequent"))
        mass, many = np.zeros(self.classes), np.zeros(self.classes)
        for r in classed.groupBy("cls").agg(F.sum("c").alias("c"), F.count("*").alias("v")).collect():
            mass[r.cls], many[r.cls] = r.c, r.v
        common = F.broadcast(classed.where("frequent").select("word", F.col("c").alias("c1"), F.col("cls").alias("cls1")))
        met = vocab.drop("n").join(common, "word", "left")
        # Rows that know their word already get a key of their own, which spreads them and meets nothing.
        met = met.withColumn("key", F.when(F.col("c1").isNull(), F.col("word")).otherwise(F.concat_ws(" ", F.lit(END), "block", "at")))
        rare = classed.where("not frequent").select(F.col("word").alias("key"), "c", "cls")
        unmet = F.when(F.col("word") == END, self.classes - 1).otherwise(kind)
        known = met.join(rare, "key", "left").select("block", "at", F.coalesce("c1", "c", F.lit(0).cast("long")).alias("c"), F.coalesce(F.col("cls1"), F.col("cls"), unmet).alias("cls"))
        texts = cut_up.df.where("word is null").select("block", "doc_id", "held_out", "ids")
        tokens, distinct, n_classes = int(self.tokens), int(self.distinct), self.classes

        def finish(left: pa.Table, right: pa.Table) -> pa.Table:
            c, cls = np.zeros(len(left), np.int64), np.zeros(len(left), np.uint16)
            at = left["at"].to_numpy()
            c[at], cls[at] = left["c"].to_numpy(), left["cls"].to_numpy()
            base = np.log10((c + SMOOTH) / (tokens + SMOOTH * (distinct + 1)))
            within = np.where((cls >= words) & (cls < n_classes - 1), np.log10((c + SMOOTH) / (mass[cls] + SMOOTH * (many[cls] + 1))), 0.0)
            unzip, press = zstandard.ZstdDecompressor().decompress, zstandard.ZstdCompressor(level=1).compress
            cols: list[list] = [[], [], [], [], []]
            for ids in right["ids"]:
                i = np.frombuffer(unzip(ids.as_buffer()), np.uint32)
                for col, x in zip(cols, (len(i), int((c[i] > 0).sum()), float(base[i].sum()), float(within[i].sum()), press(cls[i].tobytes())), strict=True):
                    col.append(x)
            return pa.table([right["doc_id"], right["held_out"], pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.float64()), pa.array(cols[3], pa.float64()), pa.array(cols[4], pa.binary())], ["doc_id", "held_out", "n_tokens", "n_known", "base_score", "within", "seq"])

        done = known.groupBy("block").cogroup(texts.groupBy("block")).applyInArrow(finish, "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, within double, seq binary")
        self.texts = Stored(done, "lm-texts")
        cut_up.drop()
        counts.drop()
        self.share = (mass + SMOOTH) / (mass + SMOOTH).sum()
        rows = self.training().count()
        # The hash bound keeps about SEED_DOCS * 1.2 + 60 texts, equal rows once; the limit makes the bound hard.
        draw = F.pmod(F.xxhash64("doc_id", "n_tokens", "base_score"), F.lit(1 << 40))
        drawn = self.training().select(draw.alias("draw"), "seq").where(F.col("draw") < int(min(1.0, (1.2 * SEED_DOCS + 60) / max(rows, 1)) * (1 << 40)))
        sample = [unpack(r.seq) for r in drawn.dropDuplicates(["draw"]).orderBy("draw").limit(SEED_DOCS).collect()]
        self.model = seeded(sample, self.share, states)
        self.trace: list[float] = []
        for _ in range(rounds if rows else 0):
            self.model = self.round()
            if len(self.trace) > 1 and self.trace[-1] - self.trace[-2] < SETTLED * abs(self.trace[-1]):
                break

    def training(self) -> DataFrame:
        return self.texts.df.where("not held_out")

    def round(self) -> Model:
        """One Baum-Welch round over all training texts."""
        model, s, c = self.model, len(self.model.start), self.classes

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            start, step, emit, fit, some = np.zeros(s), np.zeros((s, s)), np.zeros((c, s)), 0.0, False
            for part in pooled(batches, 0):
                a, b, e, f = expect(model, part)
                start, step, emit, fit, some = start + a, step + b, emit + e, fit + f, True
            if some:
                flat = np.concatenate((start, step.ravel(), emit.ravel(), [fit]))
                at = np.flatnonzero(flat)
                yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(flat[at])], ["at", "x"])
            hand_back()

        flat = np.zeros(s + s * s + c * s + 1)
        for r in self.training().select("seq").mapInArrow(run, "at long, x double").groupBy("at").agg(F.sum("x").alias("x")).collect():  # the model's size
            flat[r["at"]] = r["x"]
        self.trace.append(float(flat[-1]))
        return improved((flat[:s], flat[s : s + s * s].reshape(s, s), flat[s + s * s : -1].reshape(c, s)), self.share)

    def scores(self) -> DataFrame:
        """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) of every text."""
        model, tokens = self.model, int(self.tokens)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                score = forward(model, list(map(unpack, batch.column(6).to_pylist()))) + batch.column(5).to_numpy()
                yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(4)), pa.array(np.full(batch.num_rows, tokens)), batch.column(4), pa.array(score)], ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])
            hand_back()

        return self.texts.df.mapInArrow(run, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")
