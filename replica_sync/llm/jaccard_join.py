"""Similarity join of word-shingle sets by prefixes under several global orders.

Two sets of similarity t or more differ in at most d = n - ceil(t n) elements of the one of size n, so under any
order of all shingles their first d + 1 elements meet. A single order leaves candidates that meet by
chance; here a pair must meet under every one of several orders, early enough for the sizes of both, before its
sets are compared. All orders put
rare shingles first (exact corpus counts, or their binary logarithm), with different hashes within equal
counts, so that passages which many documents share hardly ever are in a prefix, and shingles that occur in one document only,
which meet nothing, need not be indexed.

A pair must also pass by the sketches of its sets: each element turns one bit, so that what two sets have in common
cancels, and two sketches differ in no more bits than their sets have elements outside each other. Copies with more changes than
a link allows, of which a large group makes a square of pairs that meet under every order, end there, before a row is made for them.

Documents of equal sets are one node. Within the documents that share a prefix element, a few pivots at a
time are compared with all of other components; documents that fell into one component need no further
comparison, and a compared pivot leaves its group. This goes on until no group holds two components, so
no link between components is lost and no group is paired with itself at once.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from replica_sync.llm.blocks import NONE, REQUEST, block_count, block_of, corrected, counted, in_blocks, key_bits, range_count, replies, request_table, requests
from replica_sync.llm.common import Words, dropped, kept_as_table, mixed, pick, small_batches, texts_of, trim
from replica_sync.llm.graphs import components, nearer

SHINGLE, PERCENT, ORDERS = 3, 90, 3
#: Words of 64 bits in a set's sketch.
SKETCH = 8


class Shingles:
    """The distinct shingle hashes of many texts: .doc and .hash, sorted by both; .size of each text's set."""

    #: Bytes of text that are shingled at once; longer texts alone.
    PIECE = 1 << 20

    def __init__(self, texts: list[bytes], width: int = SHINGLE):
        share = np.cumsum([len(t) for t in texts], dtype=np.int64) // self.PIECE
        cuts = [0, *(np.flatnonzero(np.diff(share)) + 1).tolist(), len(texts)] if texts else [0, 0]
        pieces = [self._distinct(texts[i:j], width) for i, j in zip(cuts, cuts[1:])]
        self.hash = np.concatenate([h for h, _ in pieces])
        self.doc = np.concatenate([d + i for (_, d), i in zip(pieces, cuts)])
        self.size = np.bincount(self.doc, minlength=len(texts))
        self.first = np.cumsum(self.size) - self.size

    @staticmethod
    def _distinct(texts: list[bytes], width: int) -> tuple[np.ndarray, np.ndarray]:
        words = Words(texts)
        n = len(texts)
        count = words.count
        rolled = words.hash.copy()
        for k in range(1, width):
            after = np.concatenate([words.hash[k:], np.zeros(min(k, len(words.hash)), dtype=np.uint64)])
            inside = np.arange(len(words.hash)) - words.first[words.doc] + k < count[words.doc]
            # a text of fewer words than the width is one shingle: what is missing stays out
            rolled = np.where(inside, mixed(rolled * np.uint64(0x9FB21C651E98DF25) + after), rolled)
        place = np.arange(len(words.hash)) - words.first[words.doc]
        keep = place <= np.maximum(count[words.doc] - width, 0)
        hashes, doc = rolled[keep], words.doc[keep]
        order = np.argsort(hashes)
        order = order[np.argsort(doc[order].astype(np.uint16 if n <= 1 << 16 else np.int64), kind="stable")]
        hashes, doc = hashes[order], doc[order]
        new = np.ones(len(hashes), dtype=bool)
        new[1:] = (hashes[1:] != hashes[:-1]) | (doc[1:] != doc[:-1])
        return hashes[new], doc[new]

    def node(self) -> list[bytes]:
        """16 bytes that stand for each set."""
        sums = []
        for salt in (0x1B873593CC9E2D51, 0xE6546B64A24BAED5):
            run = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(mixed(self.hash ^ np.uint64(salt)), dtype=np.uint64)])
            sums.append(run[self.first + self.size] - run[self.first])
        raw = np.stack(sums, axis=1).astype(">u8").tobytes()
        return [raw[i : i + 16] for i in range(0, len(raw), 16)]


def allowed_misses(n: np.ndarray, percent: int = PERCENT) -> np.ndarray:
    """How many elements a set of size n can have outside a linked one."""
    return n - -(-percent * n // 100)


def sketches(hashes: np.ndarray, doc: np.ndarray, n: int) -> np.ndarray:
    """A row of SKETCH words for each of n sets: every element turns one bit."""
    out = np.zeros(n * SKETCH, dtype=np.uint64)
    word = (hashes >> np.uint64(6)) % np.uint64(SKETCH)
    np.bitwise_xor.at(out, doc * SKETCH + word.astype(np.int64), np.uint64(1) << (hashes & np.uint64(63)))
    return out.reshape(n, SKETCH)


def shingle_nodes(rows: DataFrame, blocks: int, width: int) -> DataFrame:
    """doc_id, address (of the text), n_shingles, node, block of every row: one narrow pass."""

    def run(batches):
        for batch in small_batches(batches, "text"):
            found = Shingles(texts_of(batch), width)
            yield pa.record_batch([batch.column(0), batch.column(2), pa.array(found.size.astype(np.int64)), pa.array(found.node(), pa.binary()), batch.column(3)], names=["doc_id", "address", "n_shingles", "node", "block"])
        trim()

    marked = rows.withColumns({"address": address_of(F.col("text")), "block": block_of(rows, blocks)})
    return marked.mapInArrow(run, f"doc_id {dict(rows.dtypes)['doc_id']}, address binary, n_shingles bigint, node binary, block bigint")


def address_of(text: Column) -> Column:
    """16 bytes that stand for a text; null counts as empty."""
    return F.unhex(F.md5(F.coalesce(text, F.lit("")).cast("binary")))


INDEXED = "node binary, n bigint, alone bigint, sketch array<bigint>, shingles array<bigint>, " + ", ".join(f"prefix{k} array<bigint>" for k in range(ORDERS))


def indexed_sets(rows: DataFrame, lead: DataFrame, width: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """The sets that can have partners, one per node, with their prefixes (of shared elements only) under each order.

    rows: doc_id, text; lead: block and node (of), one row for each set: the block's first row with it stands for it.
    Counts are exchanged under the first bits of the shingles: where two meet, both count as more
    frequent than they are, the same in every block, so that no order changes between sets and no element is taken for a lone one.
    """
    n, bits = block_count(rows), key_bits(rows)
    blocks = in_blocks(rows, n)
    parts = range_count(rows, n)

    def once(table: pa.Table, wanted: set[bytes]) -> tuple[Shingles, list[bytes], np.ndarray, np.ndarray]:
        """All sets, their nodes, the rows that stand for a wanted node, and the places of those rows' elements."""
        found = Shingles(texts_of(table.combine_chunks().to_batches()[0]), width)
        nodes, first = found.node(), {}
        for i, node in enumerate(nodes):
            if node in wanted and found.size[i]:
                first.setdefault(node, i)
        docs = np.array(sorted(first.values()), dtype=np.int64)
        chosen = np.zeros(len(found.size), dtype=bool)
        chosen[docs] = True
        return found, nodes, docs, np.flatnonzero(chosen[found.doc])

    def short(hashes: np.ndarray) -> np.ndarray:
        return hashes >> np.uint64(64 - bits)

    def ask(table: pa.Table, wanted: pa.Table) -> pa.Table:
        rows = []
        if table.num_rows:
            found, _, _, at = once(table, set(wanted.column("of").to_pylist()))
            rows = list(requests(table.column("block")[0].as_py(), NONE, counted(short(found.hash[at]))[:2], parts, bits))
        out = request_table(rows)
        trim()
        return out

    def index(table: pa.Table, answers: pa.Table) -> pa.Table:
        kinds = [pa.binary(), pa.int64(), pa.int64()] + [pa.list_(pa.int64())] * (2 + ORDERS)
        names = [x.split()[0] for x in INDEXED.split(", ")]
        if not table.num_rows:
            return pa.table([pa.array([], k) for k in kinds], names=names)
        found, nodes, docs, at = once(table, {x for x in answers.column("of").to_pylist() if x is not None})
        keys, count, place = counted(short(found.hash[at]))
        told = [(p, x) for p, x in zip(answers.column("part").to_pylist(), answers.column("grams").to_pylist()) if x is not None]
        total = corrected(keys, count, told, parts, bits)
        doc, hashes, frequency = found.doc[at], found.hash[at], total[place]
        sketch = sketches(hashes, doc, len(found.size)).view(np.int64)
        del place, keys, count, total
        # under every order the elements that no other set has come first; what they leave of the prefix is shared ones
        alone = np.bincount(doc[frequency == 1], minlength=len(found.size))
        room = allowed_misses(found.size, percent) + 1 - alone
        kept = np.flatnonzero((frequency > 1) & (room[doc] > 0))
        doc, hashes, frequency = doc[kept], hashes[kept], frequency[kept]
        held = np.bincount(doc, minlength=len(found.size))
        prefixes = []
        for k in range(ORDERS):
            rank = frequency if k == 0 else np.floor(np.log2(frequency)).astype(np.int64)
            order = np.lexsort((mixed(hashes + np.uint64(0x632BE59BD9B4E019 * (k + 1) % 2**64)), rank, doc))
            nth = np.arange(len(order)) - (np.cumsum(held) - held)[doc[order]]
            take = order[nth < room[doc[order]]]
            own = np.bincount(doc[take], minlength=len(found.size))
            prefixes.append((take, np.cumsum(own) - own, own))
        alive = [i for i in docs.tolist() if all(own[i] for _, _, own in prefixes)]
        signed = found.hash.astype(np.uint64).view(np.int64)
        local = hashes.view(np.int64)
        columns = [[nodes[i] for i in alive], [int(found.size[i]) for i in alive], [int(alone[i]) for i in alive], [sketch[i] for i in alive], [signed[found.first[i] : found.first[i] + found.size[i]] for i in alive]]
        columns += [[local[take[start[i] : start[i] + own[i]]] for i in alive] for take, start, own in prefixes]
        out = pa.table([pa.array(c, k) for c, k in zip(columns, kinds)], names=names)
        trim()
        return out

    asked = blocks.groupBy("block").cogroup(lead.groupBy("block")).applyInArrow(ask, REQUEST)
    answered = replies(asked).select("block", "part", "grams", F.lit(None).cast("binary").alias("of"))
    right = answered.unionByName(lead.select("block", F.lit(0).alias("part"), F.lit(None).cast("binary").alias("grams"), "of"))
    return blocks.groupBy("block").cogroup(right.groupBy("block")).applyInArrow(index, INDEXED)


def least_common(n: Column, m: Column, percent: int = PERCENT) -> Column:
    """Elements that sets of n and m elements have in common if they link."""
    return F.ceil(percent * (n + m) / (100 + percent))


def sketches_near(least: Column) -> Column:
    """Whether sets of n and b_n elements can have so many in common, by their sketches: no pair that links is refused."""
    differ = [F.bit_count(F.get("sketch", F.lit(i)).bitwiseXOR(F.get("b_sketch", F.lit(i)))) for i in range(SKETCH)]
    return reduce(Column.__add__, differ) <= F.col("n") + F.col("b_n") - 2 * least


def compared(pairs: DataFrame, sets: DataFrame, percent: int = PERCENT) -> DataFrame:
    """Of pairs (a, b) of nodes those that pass under all other orders and whose sets are similar enough.

    Under each order what comes before the first element in common is missing on the other side, so that
    it can be no more than n less the least number in common. Whole sets are read only for pairs that pass.
    """
    others = [f"prefix{k}" for k in range(1, ORDERS)]
    both = pairs
    for x in "ab":
        both = both.join(sets.select(F.col("node").alias(x), *[F.col(c).alias(f"{x}_{c}") for c in ("n", "alone", *others)]), x)
    least = least_common(F.col("a_n"), F.col("b_n"), percent)
    for c in others:
        first = F.get(F.array_intersect(f"a_{c}", f"b_{c}"), F.lit(0))
        for x in "ab":
            both = both.where(F.col(f"{x}_alone") + F.array_position(f"{x}_{c}", first) - 1 + least <= F.col(f"{x}_n"))
    passed = kept_as_table(both.select("a", "b", "a_n", "b_n"), "passed-pairs")
    whole = passed
    for x in "ab":
        whole = whole.join(sets.select(F.col("node").alias(x), F.col("shingles").alias(f"{x}_shingles")), x)
    common = F.size(F.array_intersect("a_shingles", "b_shingles"))
    linked = whole.withColumn("common", common).where(100 * F.col("common") >= percent * (F.col("a_n") + F.col("b_n") - F.col("common"))).select("a", "b")
    links = kept_as_table(linked, "links")
    dropped(passed)
    return links


def linked_nodes(sets: DataFrame, percent: int = PERCENT, pivots: int = 8) -> DataFrame:
    """(node, root) of all nodes with a link; root stands for the component.

    Between rounds roots are only brought nearer (each is reached by links); the last call settles them.
    """
    sets = kept_as_table(sets, "shingle-sets")
    posted = sets.select("node", "n", "alone", "sketch", F.posexplode("prefix0").alias("at", "token")).select("token", "node", "n", "sketch", (F.col("alone") + F.col("at")).alias("place"))
    several = posted.groupBy("token").count().where(F.col("count") > 1).select("token")
    open_ = kept_as_table(posted.join(several, "token").withColumn("root", F.col("node")), "postings")
    links, roots = None, None
    while True:
        pivot = F.pmod(F.xxhash64("node"), F.lit(pivots))
        chosen = kept_as_table(open_.groupBy("token", pivot.alias("slot")).agg(F.min(F.struct("node", "n", "place", "root", "sketch")).alias("p")).select("token", F.col("p.node").alias("b"), F.col("p.n").alias("b_n"), F.col("p.place").alias("b_place"), F.col("p.root").alias("b_root"), F.col("p.sketch").alias("b_sketch")), "pivots")
        least = least_common(F.col("n"), F.col("b_n"), percent)
        near = (F.col("place") + least <= F.col("n")) & (F.col("b_place") + least <= F.col("b_n")) & (F.col("root") != F.col("b_root")) & sketches_near(least)
        pairs = open_.join(chosen, "token").where(near).select(F.least("node", "b").alias("a"), F.greatest("node", "b").alias("b")).distinct()
        new = compared(pairs, sets, percent)
        left = open_.join(chosen.select("token", F.col("b").alias("node")), ["token", "node"], "left_anti")
        if not new.isEmpty():
            links = new if links is None else kept_as_table(links.unionByName(new), "links")
            roots = nearer(links, roots)
            left = left.drop("root").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
        left = kept_as_table(left, "postings")
        spread = left.groupBy("token").agg(F.min("root").alias("low"), F.max("root").alias("high")).where(F.col("low") != F.col("high")).select("token")
        rest = kept_as_table(left.join(spread, "token"), "postings")
        dropped(chosen, open_, left)
        open_ = rest
        if open_.isEmpty():
            return components(links, roots) if links is not None else sets.select("node", F.col("node").alias("root")).limit(0)
        pivots *= 8


def grouped_rows(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """doc_id, address, n_shingles, component (a node that stands for it), component_id of every row."""
    rows = pick(docs, doc_id=doc_id, text=text)
    nodes = kept_as_table(shingle_nodes(rows, block_count(rows), width), "shingle-nodes")
    classes = kept_as_table(nodes.where("n_shingles > 0").groupBy("node").agg(F.min("doc_id").alias("least_id"), F.min("block").alias("block")), "shingle-classes")
    leaders = classes.select("block", F.col("node").alias("of"))
    roots = linked_nodes(indexed_sets(rows, leaders, width, percent), percent)
    least = roots.join(classes, "node").groupBy("root").agg(F.min("least_id").alias("component_id"))
    linked = roots.join(least, "root").select(F.col("node").alias("of"), "root", "component_id")
    found = classes.join(linked, F.col("node") == F.col("of"), "left").select(F.col("node").alias("of"), F.coalesce("root", "node").alias("component"), F.coalesce("component_id", "least_id").alias("component_id"))
    alone = F.col("n_shingles") == 0
    return nodes.join(found, F.col("node") == F.col("of"), "left").select("doc_id", "address", "n_shingles", F.when(~alone, F.col("component")).alias("component"), F.when(alone, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"))


def similar_documents(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id of every row.

    component_id: the smallest doc_id that links reach, its own included. Texts of fewer words than the width
    are one shingle; texts without words (null too) have none and are alone. Repeated rows are one node. A
    null doc_id is never the smallest unless all are null. An empty table gives an empty result; other
    columns are not read.
    """
    return grouped_rows(docs, doc_id, text, width, percent).select("doc_id", "n_shingles", "component_id")


def one_of_each(docs: DataFrame, width: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """The rows of docs (doc_id, text and others) that stand for their groups of similar texts: in each the smallest doc_id.

    Rows of one id are told apart by their texts: if several of a group have its smallest id, the text of the
    smallest digest stays; a repeated row stays once. Texts without words (null too) are alone, one for each id. Rows without
    an id stay, all of them. An empty table gives an empty result; other columns go along.
    """
    grouped = grouped_rows(docs.where("doc_id is not null"), width=width, percent=percent)
    first = grouped.where("component is not null").groupBy("component").agg(F.min(F.struct("doc_id", "address")).alias("f")).select("f.*")
    alone = grouped.where("component is null").select("doc_id", "address").distinct()
    leaders = kept_as_table(first.unionByName(alone).select(F.col("doc_id").alias("leading id"), F.col("address").alias("leading text")), "leaders")
    named = docs.where("doc_id is not null").withColumn("text address", address_of(F.col("text")))
    same = (F.col("doc_id") == F.col("leading id")) & (F.col("text address") == F.col("leading text"))
    kept = named.join(leaders.hint("merge"), same, "left_semi").dropDuplicates(["doc_id", "text address"]).drop("text address")
    return kept.unionByName(docs.where("doc_id is null"))
