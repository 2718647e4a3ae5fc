"""Hidden Markov language model over word classes, trained by Baum-Welch, with an exact scaled forward score.

A token is emitted in two steps: the hidden state draws a class, the class draws the word. Frequent words are classes
of their own; all other words, seen or not, fall into classes by their last bytes and form. A class gives each of its words
``(c + d) / (T + d * (V + 1))`` from the counts of the whole training corpus (T tokens and V words in the class, one share for
unseen words), so the score of a text is the log-probability of a distribution that sums to one.

Training: word counts of all training texts; then passes of Baum-Welch over the class sequences of all training texts,
where every partition adds up its expected counts and Spark sums the partitions. Long texts are worked on as windows side by side, each of
which begins ``HALO`` tokens before and ends ``HALO`` tokens after the tokens and transitions that it counts, so that both recursions
have settled on what the text says there: every token and every transition of a text counts once, those across borders as well.
Scoring: the forward recursion over the whole text, scaled at every step; the rest of texts longer than most beside them runs as
windows whose state-to-state matrices are chained, which gives the same number.

Words are known by a 64-bit hash (:mod:`textkernel`): words of up to eight bytes and equal length never share one, others with a
chance of 2**-64 a pair.

Defined results: null counts as empty; an empty text is one end token. With no training text, N and V are 0, every base
term is that of an unseen token and the model is the untrained start. Rows are scored each on its own, repeated ids too.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain.llm.batches import in_batches
from finegrain.llm.rows import column
from finegrain.llm.textkernel import FOLD, NOT_SPACE, Words, blocks, mix, words_of
from finegrain.sources.staging import staged

DELTA = 0.1
#: Words that are classes of their own (at most), classes by form, hidden states, tokens of a window, passes of Baum-Welch.
TOP_WORDS, FORM_CLASSES, STATES, WINDOW, PASSES = 1500, 512, 8, 64, 6
#: Tokens that a training window counts, and those before and after it that its recursions run in over.
TRAIN_WINDOW, HALO = 256, 32
#: Tokens whose emission counts are added up at once, while they are in the cache.
TOGETHER = 1 << 13
#: Texts that are scored side by side as long as so many go on.
ABREAST = 32
#: A word is in the broadcast head when it has this share of all training tokens: at most 2**20 words, whatever the corpus.
HEAD_SHARE = 2.0**-20
#: Tasks that the texts of one rare or unseen word are dealt over.
TAIL_SALTS = 4
END = 0


def form_class(words: Words) -> np.ndarray:
    """The form class of every word: its last two bytes, lower-cased, and its length up to four, hashed."""
    data, last = words.data, words.ends - 1
    size = words.ends - words.starts
    byte = lambda at: FOLD[data[np.maximum(at, words.starts)]].astype(np.uint64)
    if not len(last):
        return np.zeros(0, np.int64)
    key = byte(last) | (byte(last - 1) << np.uint64(8)) | (np.minimum(size, 4).astype(np.uint64) << np.uint64(16))
    return (mix(key + np.uint64(77)) % np.uint64(FORM_CLASSES)).astype(np.int64)


@dataclass
class Vocabulary:
    """What the corpus gives to every text: the head's hashes (sorted) with counts, the top words, class totals."""

    head: np.ndarray
    head_count: np.ndarray
    top: np.ndarray
    total: int
    size: int
    class_tokens: np.ndarray
    class_words: np.ndarray

    @property
    def classes(self) -> int:
        return 1 + TOP_WORDS + FORM_CLASSES

    def class_of(self, words: Words) -> np.ndarray:
        out = 1 + TOP_WORDS + form_class(words)
        if len(self.top):
            at = np.minimum(np.searchsorted(self.top, words.hashes), len(self.top) - 1)
            hit = self.top[at] == words.hashes
            out[hit] = 1 + at[hit]
        return out

    def head_counts(self, hashes: np.ndarray) -> np.ndarray:
        """Training counts of head words, 0 for the others."""
        if not len(self.head):
            return np.zeros(len(hashes), np.int64)
        at = np.minimum(np.searchsorted(self.head, hashes), len(self.head) - 1)
        return np.where(self.head[at] == hashes, self.head_count[at], 0)


def trains(id_col: str):
    """Rows that the model learns from: the checksum of the id as text, modulo 10, is not 0 (a null id is not held out)."""
    return F.coalesce(F.pmod(F.crc32(column(id_col).cast("string").cast("binary")), F.lit(10)) != 0, F.lit(True))


def word_counts(texts: DataFrame) -> DataFrame:
    """``(hash, form, n)`` of all words of column ``text``: counted a block at a time, then summed by Spark."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hashes, forms = [], []
            for _, data, offsets in blocks(batch.column(0)):
                w = words_of(data, offsets, NOT_SPACE, FOLD)
                hashes.append(w.hashes)
                forms.append(form_class(w))
            h = np.concatenate(hashes) if hashes else np.zeros(0, np.uint64)
            f = np.concatenate(forms) if forms else np.zeros(0, np.int64)
            distinct, at, n = np.unique(h, return_index=True, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(distinct.view(np.int64)), pa.array(f[at].astype(np.int32)), pa.array(n)], names=["hash", "form", "n"])

    found = texts.select("text").transform(in_batches, run, "hash long, form int, n long")
    return found.groupBy("hash").agg(F.first("form").alias("form"), F.sum("n").alias("n"))


def build_vocabulary(counts: DataFrame, training_texts: int) -> Vocabulary:
    """Collect the bounded parts: totals, the head, the top words, class totals. ``counts`` is a staged table."""
    spark = counts.sparkSession
    sums = counts.agg(F.sum("n").alias("n"), F.count("*").alias("v")).first()
    total, size = int(sums["n"] or 0) + training_texts, int(sums["v"]) + (1 if training_texts else 0)
    least = max(1.0, total * HEAD_SHARE)
    head = counts.filter(F.col("n") >= least).select("hash", "n").toPandas()
    h, n = head["hash"].to_numpy(np.int64).view(np.uint64), head["n"].to_numpy(np.int64)
    order = np.argsort(h)
    h, n = h[order], n[order]
    top = np.sort(h[np.lexsort((h, -n))[:TOP_WORDS]])
    classes = 1 + TOP_WORDS + FORM_CLASSES
    tokens, words = np.zeros(classes), np.zeros(classes)
    tops = spark.createDataFrame([(int(x),) for x in top.view(np.int64)], "hash long")
    rest = counts.join(F.broadcast(tops), "hash", "left_anti").groupBy("form").agg(F.sum("n").alias("n"), F.count("*").alias("v"))
    for r in rest.collect():  # one row for each form class
        tokens[1 + TOP_WORDS + r["form"]], words[1 + TOP_WORDS + r["form"]] = r["n"], r["v"]
    return Vocabulary(h, n, top, total, size, tokens, words)


@dataclass
class HiddenMarkov:
    """Start, transition and emission probabilities."""

    start: np.ndarray
    step: np.ndarray
    emit: np.ndarray  # classes x states, columns sum to one


def starting_model(classes: int, states: int = STATES, seed: int = 5) -> HiddenMarkov:
    rng = np.random.default_rng(seed)
    emit = rng.dirichlet(np.full(states, 0.7), size=classes) + 0.05
    stay = 0.9
    step = np.full((states, states), (1 - stay) / max(1, states - 1))
    np.fill_diagonal(step, stay)
    return HiddenMarkov(np.full(states, 1 / states), step, emit / emit.sum(0))


def window_table(lengths: np.ndarray, window: int = WINDOW) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Cut texts of so many tokens into windows: each window's text, first token (over all texts) and length."""
    pieces = -(-lengths // window)
    text = np.repeat(np.arange(len(lengths)), pieces)
    rank = np.arange(len(text)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
    first = np.repeat(np.cumsum(lengths) - lengths, pieces) + rank * window
    return text, first, np.minimum(window, lengths[text] - rank * window)


def expected_counts(model: HiddenMarkov, symbols: np.ndarray, lengths: np.ndarray, window: int = TRAIN_WINDOW, halo: int = HALO) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """Baum-Welch's E step over the sequences: start, transition and emission counts, and the log-likelihood.

    A window counts its tokens and the transitions into them; its recursions begin ``halo`` tokens earlier and end ``halo`` later, where
    the text has so many. Arrays are states by tokens, the tokens step by step: a step's windows lie side by side, the longest first.
    """
    states, classes = len(model.start), len(model.emit)
    start, trans, emit = np.zeros(states), np.zeros((states, states)), np.zeros((classes, states))
    if not len(lengths):
        return start, trans, emit, 0.0
    text, first, size = window_table(lengths, window)
    ends = np.cumsum(lengths)
    before = np.minimum(halo, first - (ends - lengths)[text])
    after = np.minimum(halo, ends[text] - first - size)
    # what is read, and from which to which step it counts
    begin, span, lo = first - before, before + size + after, before
    hi = lo + size
    order = np.argsort(-span, kind="stable")
    begin, span, lo, hi = begin[order], span[order], lo[order], hi[order]
    head = begin == (ends - lengths)[text][order]
    steps = int(span[0])
    live = np.searchsorted(-span, -np.arange(steps), "left")  # windows longer than t
    at = np.concatenate([[0], np.cumsum(live)]).tolist()
    live = live.tolist()
    # between these steps all windows count, whichever are live
    late, early = int(lo.max()), int(hi[hi < span].min(initial=steps))
    emits, turned = np.ascontiguousarray(model.emit.T), np.ascontiguousarray(model.step.T)
    drawn, scales, alphas = np.empty(at[-1], np.int64), np.empty(at[-1]), np.empty((states, at[-1]))
    for t, n in enumerate(live):
        here = slice(at[t], at[t + 1])
        np.take(symbols, begin[:n] + t, out=drawn[here], mode="clip")
        a = np.where(head, model.start[:, None], _stationary(model.step)[:, None]) if t == 0 else turned @ alphas[:, at[t - 1] : at[t - 1] + n]
        a *= np.take(emits, drawn[here], axis=1)
        c = a.sum(0, out=scales[here])
        np.multiply(a, 1 / c, out=alphas[:, here])
    # the draws' symbols, those that count nowhere as one class more
    kept = drawn.copy()
    for t, n in enumerate(live):
        if not late <= t < early:
            kept[at[t] : at[t + 1]][(t < lo[:n]) | (t >= hi[:n])] = classes
    likelihood = float(np.log(scales)[kept < classes].sum())
    # the alphas become the states' shares: scaled so, their sum is one at every token
    beta, done = np.ones((states, live[-1])), at[-1]
    for t in range(steps - 1, -1, -1):
        n = live[t]
        if t + 1 < steps:
            m, then = live[t + 1], slice(at[t + 1], at[t + 2])
            back = np.take(emits, drawn[then], axis=1)
            back *= beta
            back *= 1 / scales[then]
            beta = np.ones((states, n))
            np.matmul(model.step, back, out=beta[:, :m])
            if not late <= t + 1 < early:
                back *= (lo[:m] <= t + 1) & (t + 1 < hi[:m])
            trans += alphas[:, at[t] : at[t] + m] @ back.T
        alphas[:, at[t] : at[t + 1]] *= beta
        if done - at[t] >= TOGETHER or t == 0:
            for k in range(states):
                emit[:, k] += np.bincount(kept[at[t] : done], alphas[k, at[t] : done], minlength=classes + 1)[:classes]
            done = at[t]
    start += alphas[:, : live[0]][:, head].sum(1)
    return start, trans * model.step, emit, likelihood


def _stationary(step: np.ndarray) -> np.ndarray:
    p = np.full(len(step), 1 / len(step))
    for _ in range(200):
        p = p @ step
    return p / p.sum()


def updated(start: np.ndarray, trans: np.ndarray, emit: np.ndarray) -> HiddenMarkov:
    """Baum-Welch's M step with small pseudo-counts, so that every class has a probability in every state."""
    start, trans = start + 0.1, trans + 0.1
    emit = emit + 0.01 + 1e-5 * emit.sum(0) / len(emit)
    return HiddenMarkov(start / start.sum(), trans / trans.sum(1, keepdims=True), emit / emit.sum(0))


def forward_log10(model: HiddenMarkov, symbols: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Exact log10 likelihood of every sequence (each of one symbol at least).

    Texts run side by side while ``ABREAST`` of them go on. The rest of longer ones is cut into windows that run side by side from each
    state; the scaled state-to-state matrices are then chained along each text.
    """
    states, out = len(model.start), np.zeros(len(lengths))
    if not len(lengths):
        return out
    order = np.argsort(-lengths, kind="stable")
    size, begin = lengths[order], (np.cumsum(lengths) - lengths)[order]
    steps = int(min(size[0], max(WINDOW, size[min(len(size), ABREAST) - 1])))
    live = np.searchsorted(-size, -np.arange(steps), "left").tolist()  # texts longer than t
    emit, turned = np.ascontiguousarray(model.emit.T), np.ascontiguousarray(model.step.T)
    logs, state = np.zeros(len(lengths)), np.empty((states, len(lengths)))
    for t, n in enumerate(live):
        a = np.repeat(model.start[:, None], n, axis=1) if t == 0 else turned @ state[:, :n]
        a *= np.take(emit, np.take(symbols, begin[:n] + t), axis=1)
        c = a.sum(0)
        np.multiply(a, 1 / c, out=state[:, :n])
        logs[:n] += np.log(c)
    far = int(np.searchsorted(-size, -steps, "left"))  # texts that go on
    if far:
        logs[:far] += _chained(model, symbols, begin[:far] + steps, size[:far] - steps, state[:, :far].T.copy())
    out[order] = logs
    return out / np.log(10)


def _chained(model: HiddenMarkov, symbols: np.ndarray, begin: np.ndarray, lengths: np.ndarray, state: np.ndarray) -> np.ndarray:
    """Log-likelihoods of so many symbols from ``begin`` on, each after its ``state``; windows side by side, then chained."""
    states = len(model.start)
    text, first, size = window_table(lengths)
    first += (begin - (np.cumsum(lengths) - lengths))[text]
    order = np.argsort(-size, kind="stable")
    n = len(text)
    matrices, logs = np.empty((n, states, states)), np.zeros(n)
    short, begin = size[order], first[order]
    m = matrices[order]
    for t in range(int(size.max())):
        live = int(np.searchsorted(-short, -t, "left"))
        e = model.emit[symbols[begin[:live] + t]]
        block = ((m[:live].reshape(-1, states) @ model.step).reshape(live, states, states) if t else model.step[None]) * e[:, None, :]
        c = block.max(axis=(1, 2))
        m[:live] = block / c[:, None, None]
        logs[order[:live]] += np.log(c)
    matrices[order] = m
    head = np.flatnonzero(np.concatenate([[True], text[1:] != text[:-1]]))
    pieces = np.diff(np.append(head, n))
    out = np.zeros(len(lengths))
    for k in range(int(pieces.max())):
        on = np.flatnonzero(pieces > k)
        at = head[on] + k
        state[on] = np.einsum("ni,nij->nj", state[on], matrices[at])
        c = state[on].sum(1)
        state[on] /= c[:, None]
        out[on] += np.log(c) + logs[at]
    return out


def _encode(texts: DataFrame, vocabulary: Vocabulary) -> DataFrame:
    """For every text: its classes as 16-bit numbers with the end token, sums over head words, and the words outside the head."""
    shared = texts.sparkSession.sparkContext.broadcast(vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v: Vocabulary = shared.value
        task, serial = TaskContext.get().partitionId(), 0
        # log10 of T + d (V + 1): what a class divides its words' counts by
        divisor = np.log10(v.class_tokens + DELTA * (v.class_words + 1))
        for batch in batches:
            for row, data, offsets in blocks(batch.column(1)):
                w = words_of(data, offsets, NOT_SPACE, FOLD)
                n, of = len(offsets) - 1, w.text_of_words()
                c, k = v.head_counts(w.hashes), v.class_of(w)
                known = c > 0
                logs = np.where(known, np.log10(np.maximum(c, 1) + DELTA), 0.0)
                in_class = k > TOP_WORDS
                inside = np.where(in_class & known, logs, 0.0) - np.where(in_class, divisor[k], 0.0)
                sums = [np.bincount(of, x, minlength=n) for x in (logs, inside, known)]
                lengths = w.counts + 1
                symbols = np.full(int(lengths.sum()), END, np.uint16)
                ends = np.cumsum(lengths) - 1
                inner = np.ones(len(symbols), bool)
                inner[ends] = False
                symbols[inner] = k
                bounds = np.concatenate([[0], np.cumsum(lengths)]) * 2
                raw = symbols.tobytes()
                tail = np.flatnonzero(~known)
                cuts = np.searchsorted(of[tail], np.arange(n + 1))
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0).slice(row, n),
                        pa.array(np.arange(serial, serial + n) + (task << 33)),
                        batch.column(2).slice(row, n),
                        pa.array(lengths.astype(np.int64)),
                        pa.array(sums[0]), pa.array(sums[1]), pa.array(sums[2].astype(np.int64)),
                        pa.array([raw[bounds[i] : bounds[i + 1]] for i in range(n)], pa.binary()),
                        pa.ListArray.from_arrays(pa.array(cuts.astype(np.int32)), pa.array(w.hashes[tail].view(np.int64))),
                    ],
                    names=["id", "uid", "trains", "n_tokens", "head_logs", "class_logs", "head_known", "symbols", "tail"],
                )
                serial += n

    id_type = texts.schema["id"].dataType.simpleString()
    return texts.transform(in_batches, run, f"id {id_type}, uid long, trains boolean, n_tokens long, head_logs double, class_logs double, head_known long, symbols binary, tail array<long>")


def _symbol_blocks(column: pa.Array, least: int = 1 << 18) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Runs of rows with about ``least`` symbols: first row, end row, symbols, lengths."""
    _, at, body = column.buffers()
    offsets = np.frombuffer(at, np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64) // 2
    symbols = np.frombuffer(body, np.uint16) if body is not None else np.zeros(0, np.uint16)
    lo = 0
    while lo < len(column):
        hi = max(lo + 1, min(len(column), int(np.searchsorted(offsets, offsets[lo] + least, "right")) - 1))
        yield lo, hi, symbols[offsets[lo] : offsets[hi]].astype(np.int64), np.diff(offsets[lo : hi + 1])
        lo = hi


def baum_welch(encoded: DataFrame, classes: int, states: int = STATES, passes: int = PASSES) -> tuple[HiddenMarkov, list[float]]:
    """Train over all rows of ``encoded`` marked as training; returns the model and the log-likelihood of each pass."""
    spark, model, history = encoded.sparkSession, starting_model(classes, states), []
    rows = encoded.filter("trains").select("symbols")
    width = states + states * states + classes * states + 1
    for _ in range(passes):
        shared = spark.sparkContext.broadcast(model)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            total = np.zeros(width)
            for batch in batches:
                for _, _, symbols, lengths in _symbol_blocks(batch.column(0)):
                    start, trans, emit, likelihood = expected_counts(shared.value, symbols, lengths)
                    total += np.concatenate([start, trans.ravel(), emit.ravel(), [likelihood]])
            at = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], names=["at", "x"])

        # the sums have a fixed number of places, whatever the corpus
        summed = rows.transform(in_batches, run, "at int, x double").groupBy("at").agg(F.sum("x").alias("x")).toPandas()
        flat = np.zeros(width)
        flat[summed["at"].to_numpy(np.int64)] = summed["x"].to_numpy(np.float64)
        shared.unpersist()
        if not flat.any():
            break
        history.append(float(flat[-1]))
        trans = flat[states : states + states * states].reshape(states, states)
        model = updated(flat[:states], trans, flat[states + states * states : -1].reshape(classes, states))
    return model, history


def _likelihoods(encoded: DataFrame, model: HiddenMarkov) -> DataFrame:
    shared = encoded.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = np.zeros(len(batch))
            for lo, hi, symbols, lengths in _symbol_blocks(batch.column(0), 1 << 20):
                out[lo:hi] = forward_log10(shared.value, symbols, lengths)
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(1, len(batch.schema))), pa.array(out)], names=[*batch.schema.names[1:], "forward"])

    kept = encoded.select("symbols", "id", "uid", "trains", "n_tokens", "head_logs", "class_logs", "head_known")
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in kept.schema.fields[1:])
    return kept.transform(in_batches, run, f"{schema}, forward double")


def score_documents(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Base and model score of every row of ``docs`` (a scan: it is read twice)."""
    texts = docs.select(column(id_col).alias("id"), column(text).alias("text"), trains(id_col).alias("trains"))
    learning = texts.filter("trains")
    counts = staged(word_counts(learning), "word-counts")
    vocabulary = build_vocabulary(counts, learning.count())
    encoded = staged(_encode(texts, vocabulary), "classes")
    model, _ = baum_welch(encoded, vocabulary.classes)

    # words outside the head: few of all tokens; none of them holds more than 2**-20 of the corpus
    least = max(1.0, vocabulary.total * HEAD_SHARE)
    # a text's repeats of a word are one row; a word that no training text holds may still stand in very many texts, so words go out salted
    tail = encoded.select("uid", F.explode("tail").alias("hash")).groupBy("uid", "hash").agg(F.count("*").alias("times"))
    tail = tail.withColumn("salt", F.pmod(F.xxhash64("uid"), F.lit(TAIL_SALTS)).cast("int"))
    known = counts.filter(F.col("n") < least).select("hash", "n", F.explode(F.sequence(F.lit(0), F.lit(TAIL_SALTS - 1))).alias("salt"))
    rare = tail.join(known, ["hash", "salt"], "left")
    terms = rare.groupBy("uid").agg(
        F.sum(F.col("times") * F.log10(F.coalesce("n", F.lit(0)) + F.lit(DELTA))).alias("tail_logs"),
        F.sum(F.when(F.col("n").isNotNull(), F.col("times")).otherwise(0)).alias("tail_known"),
    )
    base = np.log10(vocabulary.total + DELTA * (vocabulary.size + 1))
    ends = vocabulary_end_log(vocabulary)
    rows = _likelihoods(encoded, model).join(terms, "uid", "left")
    tail_logs = F.coalesce("tail_logs", F.lit(0.0))
    return rows.select(
        F.col("id").alias(id_col),
        (~F.col("trains")).alias("held_out"),
        "n_tokens",
        (F.col("head_known") + F.coalesce("tail_known", F.lit(0)) + F.lit(1 if vocabulary.total else 0)).cast("long").alias("n_known"),
        F.lit(vocabulary.total).cast("long").alias("train_tokens"),
        (F.col("head_logs") + tail_logs + F.lit(ends) - F.col("n_tokens") * F.lit(float(base))).alias("base_score"),
        (F.col("forward") + F.col("class_logs") + tail_logs).alias("score"),
    )


def vocabulary_end_log(vocabulary: Vocabulary) -> float:
    """log10 of the end token's count plus delta: it ends every training text once."""
    words = int(vocabulary.class_tokens.sum()) + int(vocabulary.head_counts(vocabulary.top).sum())
    return float(np.log10(vocabulary.total - words + DELTA))
