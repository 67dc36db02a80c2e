"""Masked pseudo-likelihood of documents under a bidirectional window network.

Every token is predicted from the two tokens on either side: position-specific embeddings are added, squashed, and
turned into a distribution over token classes and, with a weight vector per token, over the tokens of a class.  Words
without a token of their own share one by hash; of a shared token each word has its exact share of the corpus, which a
join with the table of all counts adds.  A document's score is the sum of the log-probabilities of all its words, each
with itself masked.

Counts and training cover all documents.  Rows are dealt to parts by a hash of what they hold, in order of the hash; each
part trains a copy of the network, and the copies are averaged by their tokens in the executors.  What the driver gets is
one network, which depends on the rows alone, not on how they were partitioned.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import clean_columns, stage
from .words import slices, text_buffers, word_hashes, word_spans

#: Least number of words with a token of their own, tokens that the other words share by hash, classes, width of the network.
KNOWN, SHARED, CLASSES, WIDTH = 3840, 256, 64, 16
TOKENS = KNOWN + SHARED
#: Words with a token of their own grow as this times the root of the number of distinct words.
GROWTH = 8
AROUND = (-2, -1, 1, 2)
#: Tokens in a step of training, and that are scored together.
BATCH, SCORED = 8192, 16384
RATE = 0.2
#: Factor of the rate for a token's weights within its class.
OWN_RATE = 0.2
#: Bound of the output's weights.
LIMIT = 4.0
#: Parts that train a copy each: at least the first number, and the root of all tokens by the second, so that all copies
#: together grow no faster than the input.
PARTS, TOKENS_ROOT = 32, 280
_U = np.uint64
_ONES = np.ones(CLASSES, np.float32)


def _order(x: np.ndarray) -> np.ndarray:
    """Stable order of values from -1 on, by radix."""
    x = x + 1
    order = np.argsort(x.astype(np.uint16), kind="stable")
    return order if not len(x) or x.max() < 1 << 16 else order[np.argsort((x >> 16).astype(np.uint16)[order], kind="stable")]


@dataclass
class Vocabulary:
    """hashes: of known words, ascending; ids: their tokens; klass and share: class of each token and log of its share of it.

    Shared tokens follow the known ones; ``within`` is the log of one count among theirs, ``unseen`` the log share of a
    word that the corpus doesn't have.  ``counts`` is the table (word, n) of all words.  In order of their counts tokens
    have a place, and classes are runs of places that begin at ``start``.
    """

    hashes: np.ndarray
    ids: np.ndarray
    klass: np.ndarray
    share: np.ndarray
    within: np.ndarray = field(default_factory=lambda: np.zeros(SHARED))
    unseen: np.ndarray = field(default_factory=lambda: np.zeros(SHARED))
    counts: DataFrame | None = None
    n_tokens: int = 0

    def __post_init__(self):
        self.known = len(self.klass) - SHARED
        self.arrange()

    def arrange(self) -> None:
        order = np.argsort(self.klass, kind="stable")
        self.place = np.empty(len(order), np.int32)
        self.place[order] = np.arange(len(order), dtype=np.int32)
        self.start = np.searchsorted(self.klass[order], np.arange(CLASSES + 1))
        self.prior = self.share[order]
        self.mass = np.exp(self.prior)

    def tokens(self, words: np.ndarray) -> np.ndarray:
        out = self.known + (words >> _U(56)).astype(np.int32) % SHARED
        if len(self.hashes):
            at = np.minimum(np.searchsorted(self.hashes, words), len(self.hashes) - 1)
            hit = self.hashes[at] == words
            out[hit] = self.ids[at[hit]]
        return out


def _words(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    data, offsets = text_buffers(column)
    starts, ends, first = word_spans(data, offsets)
    return word_hashes(data, starts, ends), first


def count_words(rows: DataFrame) -> DataFrame:
    """(word hash, n) over all rows (text)."""
    schema = pa.schema([("word", pa.int64()), ("n", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]):
        for whole in batches:
            for batch in slices(whole, "text", 1 << 24):
                words, n = np.unique(_words(batch.column(batch.schema.get_field_index("text")))[0], return_counts=True)
                if len(words):
                    yield pa.RecordBatch.from_arrays([pa.array(words.view(np.int64)), pa.array(n.astype(np.int64))], schema=schema)

    return rows.mapInArrow(run, "word long, n long").groupBy("word").agg(F.sum("n").alias("n"))


def make_vocabulary(rows: DataFrame) -> Vocabulary:
    """The most frequent words (ties by hash) and exact counts of all tokens, one of every token added."""
    counts = stage(count_words(rows), "scoring-counts")
    n_known = max(KNOWN, int(GROWTH * counts.count() ** 0.5))
    n_tokens = n_known + SHARED
    top = counts.orderBy(F.desc("n"), "word").limit(n_known)
    known = [(r["word"], r["n"]) for r in top.collect()]
    hashes = np.array([w for w, _ in known], np.int64).view(_U)
    order = np.argsort(hashes)
    # the words that share tokens, added up in the executors
    token = F.pmod(F.shiftrightunsigned("word", 56), F.lit(SHARED))
    totals, kinds = np.ones(n_tokens, np.float64), np.zeros(SHARED, np.int64)
    for r in counts.groupBy(token.alias("token")).agg(F.sum("n").alias("n"), F.count("*").alias("words")).collect():
        totals[n_known + r["token"]] += r["n"]
        kinds[r["token"]] += r["words"]
    for i, (w, n) in enumerate(known):
        totals[i] += n
        totals[n_known + ((w >> 56) & 0xFF) % SHARED] -= n
        kinds[((w >> 56) & 0xFF) % SHARED] -= 1
    by_count = np.argsort(-totals, kind="stable")
    before = np.cumsum(totals[by_count]) - totals[by_count]
    klass, share = np.zeros(n_tokens, np.int32), np.zeros(n_tokens, np.float32)
    klass[by_count] = np.minimum((before / totals.sum() * CLASSES).astype(np.int32), CLASSES - 1)
    mass = np.bincount(klass, totals, CLASSES)
    share[:] = np.log(totals / mass[klass])
    # the one that was added to a shared token is for words that are not in the corpus, taken to be as many as those that are
    within = -np.log(totals[n_known:])
    return Vocabulary(hashes[order], order.astype(np.int32), klass, share, within, within - np.log(kinds + 1), counts, int(totals.sum()) - n_tokens)


class Network:
    """Embeddings (positions, tokens + 1, width; the last row is the margin of a text), output matrix and bias of the
    classes, and the weights of each token within its class, by place."""

    def __init__(self, seed: int = 0, tokens: int = TOKENS):
        rng = np.random.default_rng(seed)
        self.embed = (rng.standard_normal((len(AROUND), tokens + 1, WIDTH)) * 0.1).astype(np.float32)
        self.out = (rng.standard_normal((WIDTH, CLASSES)) * 0.1).astype(np.float32)
        self.bias = np.zeros(CLASSES, np.float32)
        self.own = np.zeros((tokens, WIDTH), np.float32)

    def blob(self) -> np.ndarray:
        return np.concatenate([self.embed.ravel(), self.out.ravel(), self.bias, self.own.ravel()])

    @classmethod
    def of(cls, blob: np.ndarray) -> Network:
        net = cls.__new__(cls)
        tokens = (len(blob) - (len(AROUND) + CLASSES) * WIDTH - CLASSES) // ((len(AROUND) + 1) * WIDTH)
        ends = np.cumsum([len(AROUND) * (tokens + 1) * WIDTH, WIDTH * CLASSES, CLASSES])
        embed, out, bias, own = np.split(blob, ends)
        net.embed = embed.reshape(len(AROUND), tokens + 1, WIDTH).copy()
        net.out = out.reshape(WIDTH, CLASSES).copy()
        net.bias = bias.copy()
        net.own = own.reshape(tokens, WIDTH).copy()
        return net

    def sized(self, voc: Vocabulary) -> Network:
        """This network, or one that is not trained yet if the vocabulary has another number of tokens."""
        return self if len(self.own) == len(voc.klass) else Network(tokens=len(voc.klass))

    def hidden(self, around: np.ndarray) -> np.ndarray:
        total = self.embed[0].take(around[0], axis=0)
        for k in range(1, len(AROUND)):
            total += self.embed[k].take(around[k], axis=0)
        return np.tanh(total)

    def log_classes(self, hidden: np.ndarray) -> np.ndarray:
        # hidden values are within 1 and weights within LIMIT, so the exponentials can't overflow
        z = hidden @ self.out + self.bias
        z -= np.log(np.exp(z) @ _ONES)[:, None]
        return z

    def within(self, hidden: np.ndarray, tokens: np.ndarray, voc: Vocabulary) -> Iterator[tuple]:
        """For each class of a batch: its rows, run of places, targets in it, and for each row the probabilities of the
        run's tokens divided by their shares, unscaled, and the sum of those probabilities."""
        order = _order(place := voc.place[tokens])
        place = place[order]
        cuts = np.searchsorted(place, voc.start)
        for k in np.flatnonzero(np.diff(cuts)).tolist():
            rows, run = order[cuts[k] : cuts[k + 1]], slice(int(voc.start[k]), int(voc.start[k + 1]))
            # as with the classes; the shares of a class add up to 1
            z = hidden.take(rows, axis=0) @ self.own[run].T
            np.exp(z, out=z)
            yield rows, run, place[cuts[k] : cuts[k + 1]] - run.start, z, z @ voc.mass[run]

    def drawn(self, hidden: np.ndarray, tokens: np.ndarray, voc: Vocabulary) -> Iterator[tuple]:
        """For each class of a batch: its rows, their hidden values, the distinct places of its tokens, where each begins
        among the rows and how often it is there, and each row's target among those.

        A batch's tokens of a class are draws by their shares of it.  A sum over the whole class of shares times values is
        thus estimated by one over the draws, in which a token's share becomes its count: training costs as much as the
        batch has tokens, however large classes are.  Scores use the whole class.
        """
        order = _order(place := voc.place[tokens])
        place = place[order]
        new = np.concatenate(([True], place[1:] != place[:-1]))
        index, first = np.cumsum(new) - 1, np.flatnonzero(new)
        count = np.diff(np.append(first, len(place))).astype(np.float32)
        cuts = np.searchsorted(place, voc.start)
        for k in np.flatnonzero(np.diff(cuts)).tolist():
            lo, hi = int(cuts[k]), int(cuts[k + 1])
            here = slice(int(index[lo]), int(index[hi - 1]) + 1)
            rows = order[lo:hi]
            yield rows, hidden.take(rows, axis=0), place[first[here]], first[here] - lo, count[here], index[lo:hi] - here.start

    def log_within(self, hidden: np.ndarray, tokens: np.ndarray, voc: Vocabulary) -> np.ndarray:
        """Log-probability of each token among those of its class."""
        out = np.zeros(len(tokens), np.float32)
        for rows, run, target, z, total in self.within(hidden, tokens, voc):
            out[rows] = np.log(z[np.arange(len(rows)), target] / total) + voc.prior[run][target]
        return out

    def step(self, around: np.ndarray, classes: np.ndarray, rate: float, tokens: np.ndarray | None = None, voc: Vocabulary | None = None) -> None:
        """One step of gradient descent on a batch.  Without tokens only classes are learned."""
        n = len(classes)
        h = self.hidden(around)
        d = h @ self.out
        d += self.bias
        np.exp(d, out=d)
        d /= (d @ _ONES)[:, None]
        d[np.arange(n), classes] -= 1
        dh = d @ self.out.T
        dh *= 1 - h * h
        if tokens is not None:
            slope = np.zeros_like(h)
            for rows, mine, places, begins, count, target in self.drawn(h, tokens, voc):
                own = self.own.take(places, axis=0)
                z = mine @ own.T
                np.exp(z, out=z)
                z *= count
                total = z @ np.ones(len(places), np.float32)
                slope[rows] = (z @ own) / total[:, None] - own.take(target, axis=0)
                g = z.T @ (mine / total[:, None])
                g -= np.add.reduceat(mine, begins, axis=0)
                # a step per token, and a batch that repeats one word takes no longer step than others
                g *= (np.float32(rate * OWN_RATE) / count)[:, None]
                own -= g
                np.clip(own, -LIMIT, LIMIT, out=own)
                self.own[places] = own
            dh += slope * (1 - h * h)
        # rates are per token for the rows of an embedding and per batch for the rest
        self.out = np.clip(self.out - rate * 10 * (h.T @ d) / n, -LIMIT, LIMIT)
        self.bias = np.clip(self.bias - rate * 10 * d.sum(axis=0) / n, -LIMIT, LIMIT)
        dh *= rate
        for k in range(len(AROUND)):
            order = _order(around[k])
            rows = around[k][order]
            first = np.flatnonzero(np.concatenate(([True], rows[1:] != rows[:-1])))
            sums = np.add.reduceat(dh.take(order, axis=0), first, axis=0)
            sizes = np.diff(np.append(first, n)).astype(np.float32)
            self.embed[k][rows[first]] -= sums / np.sqrt(sizes)[:, None]


def windows(tokens: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Tokens around each token of texts that start at ``first``; outside its text there is the margin, -1."""
    n, reach = len(tokens), max(AROUND)
    n_texts = len(first) - 1
    owner = np.repeat(np.arange(n_texts), np.diff(first))
    padded = np.full(n + 2 * reach * n_texts + 2 * reach, -1, np.int32)
    at = np.arange(n) + reach + 2 * reach * owner
    padded[at] = tokens
    return np.stack([padded[at + k] for k in AROUND])


class Stream:
    """Trains a network on texts as they come, in batches of ``BATCH`` tokens whatever the pieces they come in."""

    def __init__(self, net: Network, voc: Vocabulary, rate: float):
        self.net, self.voc, self.rate, self.seen = net, voc, rate, 0
        self.held = np.zeros((len(AROUND) + 1, 0), np.int32)

    def add(self, tokens: np.ndarray, first: np.ndarray) -> None:
        self.held = np.concatenate([self.held, np.vstack([windows(tokens, first), tokens[None]])], axis=1)
        n = self.held.shape[1] // BATCH * BATCH
        self._steps(n)
        self.held = self.held[:, n:]

    def _steps(self, n: int) -> None:
        for k in range(0, n, BATCH):
            tokens = self.held[-1, k : min(n, k + BATCH)]
            self.net.step(self.held[:-1, k : min(n, k + BATCH)], self.voc.klass[tokens], self.rate, tokens, self.voc)
            self.seen += len(tokens)

    def end(self) -> None:
        self._steps(self.held.shape[1])
        self.held = self.held[:, :0]


def train(rows: DataFrame, voc: Vocabulary, net: Network, rate: float = RATE) -> Network:
    """One pass over all rows (doc_id, text): every part trains a copy, then copies are averaged by numbers of tokens."""
    net = net.sized(voc)
    given = rows.sparkSession.sparkContext.broadcast((replace(voc, counts=None), net.blob()))
    n_parts = max(PARTS, int(voc.n_tokens**0.5) // TOKENS_ROOT)
    pieces = 32
    schema = pa.schema([("piece", pa.int32()), ("part", pa.int32()), ("weight", pa.float64()), ("values", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]):
        vocabulary, blob = given.value
        part, stream = None, None

        def done() -> Iterator[pa.RecordBatch]:
            if stream is None:
                return
            stream.end()
            if stream.seen:
                cut = np.array_split(stream.net.blob(), pieces)
                yield pa.RecordBatch.from_arrays([pa.array(range(pieces), pa.int32()), pa.array([part] * pieces, pa.int32()), pa.array([float(stream.seen)] * pieces), pa.array([c.tobytes() for c in cut], pa.binary())], schema=schema)

        for whole in batches:
            for batch in slices(whole, "text"):
                owners = batch.column(0).to_numpy()
                cuts = [0, *(np.flatnonzero(np.diff(owners)) + 1).tolist(), len(owners)]
                for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                    if owners[lo] != part:
                        yield from done()
                        part, stream = int(owners[lo]), Stream(Network.of(blob), vocabulary, rate)
                    words, first = _words(batch.column(1).slice(lo, hi - lo))
                    stream.add(vocabulary.tokens(words), first)
        yield from done()

    def add(batches: Iterator[pa.RecordBatch]):
        current, weight, total = None, 0.0, None

        def done() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([current], pa.int32()), pa.array([0], pa.int32()), pa.array([weight]), pa.array([(total / weight).astype(np.float32).tobytes()], pa.binary())], schema=schema)

        for batch in batches:
            for piece, _, w, values in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                if piece != current:
                    if current is not None:
                        yield done()
                    current, weight, total = piece, 0.0, 0.0
                weight, total = weight + w, total + np.frombuffer(values, np.float32).astype(np.float64) * w
        if current is not None:
            yield done()

    ddl = "piece int, part int, weight double, values binary"
    mark = F.xxhash64("text", "doc_id")
    dealt = rows.filter(F.length("text") > 0).withColumns({"hash": mark, "part": F.pmod(mark, F.lit(n_parts)).cast("int")})
    dealt = dealt.repartitionById(n_parts, "part").sortWithinPartitions("part", "hash", "doc_id").select("part", "text")
    copies = dealt.mapInArrow(run, ddl)
    made = copies.repartition("piece").sortWithinPartitions("piece", "part").mapInArrow(add, ddl).collect()
    if not made:
        return net
    return Network.of(np.concatenate([np.frombuffer(r["values"], np.float32) for r in sorted(made, key=lambda r: r["piece"])]))


def score(rows: DataFrame, voc: Vocabulary, net: Network) -> DataFrame:
    """doc_id, n_tokens, log_prob (sum) and mean_log_prob (null without tokens) of rows (doc_id, text).

    The network gives the part of each row's tokens where the row lies; words of shared tokens meet their counts by a
    join, and one number a row comes back.
    """
    given = rows.sparkSession.sparkContext.broadcast((replace(voc, counts=None), net.sized(voc).blob()))
    schema = pa.schema([("row", pa.int64()), ("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("log_prob", pa.float64()), ("words", pa.list_(pa.int64()))])

    def run(batches: Iterator[pa.RecordBatch]):
        vocabulary, blob = given.value
        own, row = Network.of(blob), TaskContext.get().partitionId() << 40
        for whole in batches:
            for batch in slices(whole, "text"):
                words, first = _words(batch.column(1))
                tokens = vocabulary.tokens(words)
                around, classes = windows(tokens, first), vocabulary.klass[tokens]
                logs = np.zeros(len(tokens) + 1)
                for k in range(0, len(tokens), SCORED):
                    hidden = own.hidden(around[:, k : k + SCORED])
                    part = own.log_classes(hidden)
                    logs[k + 1 : k + 1 + len(part)] = part[np.arange(len(part)), classes[k : k + SCORED]]
                    logs[k + 1 : k + 1 + len(part)] += own.log_within(hidden, tokens[k : k + SCORED], vocabulary)
                rare = np.flatnonzero(tokens >= vocabulary.known)
                total = np.cumsum(logs)
                sums = total[first[1:]] - total[first[:-1]]
                n = len(first) - 1
                lists = pa.ListArray.from_arrays(np.searchsorted(rare, first).astype(np.int32), words[rare].view(np.int64))
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(row, row + n)), batch.column(0), pa.array(np.diff(first)), pa.array(sums), lists], schema=schema)
                row += n

    scored = stage(rows.mapInArrow(run, "row long, doc_id long, n_tokens long, log_prob double, words array<long>"), "scoring-rows")
    rare = scored.select("row", F.explode("words").alias("word"))
    shared = F.pmod(F.shiftrightunsigned("word", 56), F.lit(SHARED)) + 1
    within, unseen = (F.element_at(F.array(*(F.lit(float(x)) for x in column)), shared.cast("int")) for column in (voc.within, voc.unseen))
    share = F.when(F.col("n").isNull(), unseen).otherwise(F.log("n") + within)
    # the table of counts is never the smaller side for long, so it is left to be split and sorted
    added = rare.join(voc.counts.hint("merge"), "word", "left").groupBy("row").agg(F.sum(share).alias("share"))
    out = scored.drop("words").join(added, "row", "left").withColumn("log_prob", F.col("log_prob") + F.coalesce("share", F.lit(0.0)))
    return out.select("doc_id", "n_tokens", "log_prob", F.when(F.col("n_tokens") > 0, F.col("log_prob") / F.col("n_tokens")).alias("mean_log_prob"))


def pseudo_likelihood(docs: DataFrame) -> DataFrame:
    """Counts, trains and scores over all rows of ``docs``.

    Null and empty texts have no tokens and score 0.  Repeated rows train and score as often as they are there.  Other
    columns are ignored; an empty table gives an empty result.
    """
    rows = clean_columns(docs, "doc_id", "text")
    rows = rows.select(rows["doc_id"].cast("long").alias("doc_id"), "text")
    voc = make_vocabulary(rows.select("text"))
    net = train(rows, voc, Network())
    return score(rows, voc, net)
