"""Language-model scores by a weighted backoff automaton.

States are the contexts seen in training (up to order-1 words; the empty one is the root). A state has an arc for
each word seen after it, weighted by the word's smoothed log-probability, which leads to the longest state
that the text then ends in; and a failure arc to the next shorter context, weighted by the share that smoothing leaves to it.
Reading a text from left to right takes one arc per token, after as many failure arcs as needed.

Smoothing: the root has (c + 0.1) / (N + 0.1 (V + 1)); a context h seen n(h) times has
(c(h w) + k p(w | shorter h)) / (n(h) + k), so its failure arc weighs k / (n(h) + k): the probabilities of
all words, with one share for all unseen ones, add up to 1 in every state. The strength k of each length of context is
the one of a ladder under which the training texts, each token left out of the counts in its turn, are likeliest.

Each block of rows (a pack) builds the part of the automaton that its texts can reach, from corpus counts of its own grams.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from replica_sync.llm.blocks import BLOCK_BYTES, NONE, REQUEST, block_count, corrected, counted, key_bits, range_count, replies, request_table, requests, unpacked
from replica_sync.llm.common import Words, kept_as_table, mixed, pick, small_batches, texts_of, trim

ORDER = 3
#: Strengths that are tried for each length of context.
LADDER = (4.0, 16.0, 64.0, 256.0)
#: Tokens that a lane of the traversal reads.
LANE = 64
#: Nodes or tokens that are weighed at once.
PIECE = 1 << 16
BEGIN, END = np.uint64(0x5BD1E9955BD1E995), np.uint64(0x27D4EB2F165667C5)


def longer(context: np.ndarray, word: np.ndarray) -> np.ndarray:
    """Keys of contexts followed by words."""
    return mixed(context * np.uint64(0x9FB21C651E98DF25) + word)


class Sequences:
    """Texts as token keys: begin, words, end; .doc of each token, .real all but begin, .start of each text, .grams (places, keys) of 2, 3, ... tokens."""

    def __init__(self, texts: list[bytes], order: int, bits: int = 64):
        words = Words(texts)
        n = words.count + 2
        self.start = np.cumsum(n) - n
        self.tokens = np.empty(int(n.sum()), dtype=np.uint64)
        self.doc = np.repeat(np.arange(len(texts)), n)
        self.tokens[self.start], self.tokens[self.start + n - 1] = BEGIN, END
        self.tokens[np.arange(len(words.hash)) + 2 * words.doc + 1] = words.hash
        self.real = np.ones(len(self.tokens), dtype=bool)
        self.real[self.start] = False
        age = np.arange(len(self.tokens)) - np.repeat(self.start, n)
        self.begin = self.key(self.tokens[self.start], 1, bits)
        self.grams: list[tuple[np.ndarray, np.ndarray]] = []
        whole = self.tokens
        for m in range(2, order + 1):
            following = longer(np.concatenate([whole[:1], whole[:-1]]), self.tokens)
            place = np.flatnonzero(age >= m - 1)
            self.grams.append((place, self.key(following[place], m, bits)))
            whole = following

    @staticmethod
    def key(hashes: np.ndarray, length: int, bits: int) -> np.ndarray:
        """The first bits of a gram's hash; the last three of them tell its length, so that grams of two lengths never meet."""
        return hashes >> np.uint64(64 - bits) & np.uint64(2**64 - 8) | np.uint64(length % 8)


def counts_of(seq: Sequences, training: np.ndarray) -> tuple[tuple, tuple]:
    """(keys, counts, place of each token) of words; (keys, counts, place of each begin and gram) of contexts and longer grams."""
    weight = training[seq.doc].astype(float)
    words = counted(seq.tokens[seq.real], weight[seq.real])
    keys = np.concatenate([seq.begin, *[k for _, k in seq.grams]])
    weights = np.concatenate([training.astype(float), *[weight[p] for p, _ in seq.grams]])
    return words, counted(keys, weights)


class BackoffAutomaton:
    """States and arcs that the texts of a block can reach.

    Nodes are the root (0), the words, and the longer grams; a seen node is a state if it is shorter than the order, and the
    target of an arc from its context. node[m][i] is the gram of m tokens that ends at token i (0 if the text is
    too short); .suffix is where a node's failure arc leads, .context where the arc to it starts.
    """

    def __init__(self, seq: Sequences, word_place: np.ndarray, word_count: np.ndarray, gram_place: np.ndarray, gram_count: np.ndarray, total: int, kinds: int):
        n, words = len(seq.tokens), len(word_count)
        self.order = len(seq.grams) + 1
        self.base = total + 0.1 * (kinds + 1)
        self.count = np.concatenate([[0.0], word_count, gram_count])  # exact below 2**53
        self.node = np.zeros((self.order + 1, n), dtype=np.int32)
        self.node[1, seq.real] = 1 + word_place
        self.node[1, seq.start] = 1 + words + gram_place[: len(seq.start)]
        at = len(seq.start)
        for m, (place, _) in enumerate(seq.grams, 2):
            self.node[m, place] = 1 + words + gram_place[at : at + len(place)]
            at += len(place)
        self.level, self.suffix, self.context = (np.zeros(len(self.count), dtype=t) for t in (np.int8, np.int32, np.int32))
        self.level[self.node[1]] = 1
        for m, (place, _) in enumerate(seq.grams, 2):
            own = self.node[m, place]
            self.level[own], self.suffix[own], self.context[own] = m, self.node[m - 1, place], self.node[m - 1, place - 1]

    def arcs(self, *ladders: tuple[float, ...]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """log10 weights of the arc to each node, and of each state's failure arc, under all settings of one strength from each
        ladder (of contexts of 1, 2, ... tokens). The arrays are used again for the next setting.
        """
        weight = (self.count + 0.1) / self.base
        arc, fail = np.log10(weight), np.zeros(len(self.count))
        level = [np.flatnonzero(self.level == m).astype(np.int32) for m in range(self.order + 1)]
        # in pieces, so that what is worked out on the way is never as long as a level
        drawn = [[(x, self.count[x], self.count[self.context[x]], self.suffix[x]) for at in range(0, len(own), PIECE) for x in [own[at : at + PIECE]]] for own in level]

        def settle(m: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
            if m > self.order:
                yield arc, fail
                return
            for k in ladders[m - 2]:  # a context that was never seen leaves all to the shorter one
                for own, count, seen, suffix in drawn[m]:
                    share = (count + k * weight[suffix]) / (seen + k)
                    weight[own], arc[own] = share, np.log10(share)
                for own, count, _, _ in drawn[m - 1]:
                    fail[own] = np.log10(k / (count + k))
                yield from settle(m + 1)

        return settle(2)

    def traverse(self, seq: Sequences) -> tuple[np.ndarray, list[np.ndarray]]:
        """For each token the node of the arc taken, and the states that were failed before, one array for each failure (0 where there is none).

        Lanes of LANE tokens are read side by side, each from left to right with its state carried on. A state is at most
        order - 1 tokens, so a lane that starts within a text finds its state by reading so many tokens before.
        """
        size = np.diff(np.append(seq.start, len(seq.tokens))) - 1  # real tokens of each text
        lanes = -(-size // LANE)
        first = np.repeat(seq.start + 1, lanes) + LANE * (np.arange(int(lanes.sum())) - np.repeat(np.cumsum(lanes) - lanes, lanes))
        text = np.repeat(seq.start, lanes)
        last = np.minimum(first + LANE, np.repeat(seq.start + 1 + size, lanes))
        taken = np.zeros(len(seq.tokens), dtype=np.int32)
        failed = [np.zeros(len(seq.tokens), dtype=np.int32) for _ in range(self.order - 1)]
        at = np.maximum(first - (self.order - 1), text + 1)
        state = np.where(at == text + 1, self.node[1, text], 0)
        state = np.where((self.count[state] > 0) & (self.order > 1), state, 0)
        while len(at):
            open_, token = np.arange(len(at)), at
            inside = at >= first
            for k in range(self.order):
                level = self.level[state[open_]]
                arc = self.node[level + 1, token[open_]]
                hit = (self.count[arc] > 0) | (level == 0)
                done = open_[hit]
                keep = inside[done]
                taken[token[done[keep]]] = arc[hit][keep]
                follow = np.where(self.level[arc[hit]] == self.order, self.suffix[arc[hit]], arc[hit])
                open_ = open_[~hit]
                if len(open_):
                    keep = inside[open_]
                    failed[k][token[open_[keep]]] = state[open_[keep]]
                    state[open_] = self.suffix[state[open_]]
                state[done] = np.where(self.count[follow] > 0, follow, 0)
            at = at + 1
            go = at < last
            at, first, last, state = at[go], first[go], last[go], state[go]
        return taken, failed

    def left_out(self, tokens: np.ndarray, *ladders: tuple[float, ...]) -> list[float]:
        """log10 probability of training tokens, each with its own occurrence taken out of the counts, under all settings."""
        sums = np.zeros(math.prod(len(x) for x in ladders))

        def settle(m: int, drawn: list[tuple[np.ndarray, np.ndarray]], shorter: np.ndarray) -> Iterator[float]:
            if m > self.order:
                yield float(np.log10(shorter).sum())
                return
            count, seen = drawn[m - 1]
            for k in ladders[m - 2]:
                yield from settle(m + 1, drawn, (count + k * shorter) / (seen + k))

        for at in range(0, len(tokens), PIECE):
            drawn = []
            for m in range(1, self.order + 1):
                own = self.node[m, tokens[at : at + PIECE]]
                drawn.append((np.maximum(self.count[own] - 1, 0), np.where(own > 0, np.maximum(self.count[self.context[own]] - 1, 0), 0)))
            sums += list(settle(2, drawn, (drawn[0][0] + 0.1) / (self.base - 1)))
        return sums.tolist()


def packed_rows(rows: DataFrame, each: int = 2 * BLOCK_BYTES) -> DataFrame:
    """block, rows: the rows of each task in packs of about so many bytes, as compressed Arrow streams. Narrow.

    A row is in one pack however long it is. Packs are numbered by task, the same on each run over the same files.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, number = [], 0, TaskContext.get().partitionId() << 24

        def pack() -> pa.RecordBatch:
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, held[0].schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
                out.write_table(pa.Table.from_batches(held).combine_chunks())
            return pa.record_batch([pa.array([number], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], names=["block", "rows"])

        for batch in small_batches(batches, "text", each // 8):
            held.append(batch)
            size += batch.get_total_buffer_size() if batch.num_rows == 1 else pc.sum(pc.binary_length(batch.column("text"))).as_py() or 0
            if size >= each:
                yield pack()
                held, size, number = [], 0, number + 1
        if held:
            yield pack()

    return rows.mapInArrow(run, "block bigint, rows binary")


def unpacked_rows(packs: pa.Table) -> tuple[int, pa.RecordBatch]:
    """The block's number and its rows."""
    return packs.column("block")[0].as_py(), pa.ipc.open_stream(packs.column("rows")[0].as_buffer()).read_all().combine_chunks().to_batches()[0]


def word_totals(rows: DataFrame, parts: int) -> tuple[int, int]:
    """Tokens and distinct tokens of the training texts (text, training), ends included: two numbers for the driver."""

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def merged() -> tuple[np.ndarray, np.ndarray]:
            return counted(np.concatenate([k for k, _ in held]), np.concatenate([c for _, c in held]))[:2]

        for batch in small_batches(batches, "text"):
            training = np.array(batch.column(1).to_pylist(), dtype=bool)
            words = Words([t for t, x in zip(texts_of(batch), training) if x])
            held.append(counted(np.append(words.hash, END), np.append(np.ones(len(words.hash)), training.sum()))[:2])
            if len(held) == 16:  # what is held stays as large as its distinct words
                held[:] = [merged()]
                if len(held[0][0]) > 1 << 20:
                    yield from request_table([(p, 0, w, g) for p, _, w, g in requests(0, held[0], NONE, parts)]).to_batches()
                    held.clear()
        if held:
            yield from request_table(list(requests(0, merged(), NONE, parts))).to_batches()
        trim()

    def add(table: pa.Table) -> pa.Table:
        split = [unpacked(x) for x in table.column("words").to_pylist()]
        totals = counted(np.concatenate([k for k, _ in split]), np.concatenate([c for _, c in split]))[1]
        return pa.table({"total": [int(totals.sum())], "kinds": [int((totals > 0).sum())]})

    found = rows.select("text", "training").mapInArrow(ask, REQUEST).groupBy("part").applyInArrow(add, "total bigint, kinds bigint")
    row = found.agg(F.sum("total").alias("total"), F.sum("kinds").alias("kinds")).first()
    return row["total"] or 0, row["kinds"] or 0


def score_texts(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", training: Column | None = None, order: int = ORDER, ladder: tuple[float, ...] = LADDER) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row; scores are log10.

    training: a boolean Column over doc_id, by default crc32(doc_id) mod 10 is not 0 (a null id counts as the
    empty string). A null or empty text is the end token alone. Repeated rows each count in training;
    an empty table gives an empty result; other columns are not read. Words are told apart by 64 bits,
    longer grams by as many as make a meeting of two less likely than one in a million.
    """
    rows = pick(docs, doc_id=doc_id, text=text)
    kind = dict(rows.dtypes)["doc_id"]
    if training is None:
        training = F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % 10 != 0
    rows = rows.withColumn("training", training)
    n, bits = block_count(rows), key_bits(rows)
    blocks = packed_rows(rows).repartition(n, "block")
    parts = range_count(rows, n)
    total, kinds = word_totals(rows, parts)
    ladders = [ladder] * (order - 1)
    settings = len(ladder) ** (order - 1)
    names = ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "scores", "left_out"]

    def prepared(table: pa.Table):
        block, batch = unpacked_rows(table)
        seq = Sequences(texts_of(batch), order, bits)
        mask = np.array(batch.column("training").to_pylist(), dtype=bool)
        return block, batch, seq, mask, *counts_of(seq, mask)

    def ask(table: pa.Table) -> pa.Table:
        block, _, _, _, words, grams = prepared(table)
        out = request_table(list(requests(block, words[:2], grams[:2], parts, bits)))
        del words, grams
        trim()
        return out

    def score(table: pa.Table, answers: pa.Table) -> pa.Table:
        _, batch, seq, mask, words, grams = prepared(table)
        told = answers.select(["part", "words", "grams"]).to_pydict()
        word_count = corrected(*words[:2], list(zip(told["part"], told["words"])), parts)
        gram_count = corrected(*grams[:2], list(zip(told["part"], told["grams"])), parts, bits)
        automaton = BackoffAutomaton(seq, words[2], word_count, grams[2], gram_count, total, kinds)
        known = word_count[words[2]]
        del words, grams, told
        seq.grams.clear()
        taken, failed = automaton.traverse(seq)
        left_out = automaton.left_out(np.flatnonzero(seq.real & mask[seq.doc]), *ladders)
        m = batch.num_rows
        add = lambda x: np.bincount(doc, x, minlength=m)
        doc, taken, failed = seq.doc[seq.real], taken[seq.real], [x[seq.real] for x in failed]
        fell = [(at, x[at]) for x in failed for at in [np.flatnonzero(x)]]
        del seq, failed, automaton.node  # the arcs' weights need the nodes alone
        scores = np.zeros((m, settings))
        for j, (arc, fail) in enumerate(automaton.arcs(*ladders)):
            weights = arc[taken]
            for at, x in fell:
                weights[at] += fail[x]
            scores[:, j] = add(weights)
        base = add(np.log10((known + 0.1) / automaton.base))
        once = [left_out if i == 0 else None for i in range(m)]
        out = pa.table([batch.column(0), pa.array(~mask), *(pa.array(x.astype(np.int64)) for x in (add(None), add(known > 0))), pa.array(np.full(m, total, dtype=np.int64)), pa.array(base), pa.array(scores.tolist(), pa.list_(pa.float64())), pa.array(once, pa.list_(pa.float64()))], names=names)
        del automaton
        trim()
        return out

    schema = f"doc_id {kind}, held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, scores array<double>, left_out array<double>"
    answered = replies(blocks.groupBy("block").applyInArrow(ask, REQUEST))
    scored = kept_as_table(blocks.groupBy("block").cogroup(answered.groupBy("block")).applyInArrow(score, schema), "lm-scores")
    sums = scored.agg(*[F.sum(F.get("left_out", F.lit(j))).alias(f"s{j}") for j in range(settings)]).first()
    best = max(range(settings), key=lambda j: (sums[j] if sums[j] is not None else 0.0, -j))
    return scored.select(*names[:-2], F.get("scores", F.lit(best)).alias("score"))
