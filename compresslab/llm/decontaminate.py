"""Benchmark decontamination by templates: numbers, names and units become typed slots.

Documents and benchmark items are read as words. A word that starts with a digit is a number (digits joined by a
point or comma are one), a known unit behind a number is a unit, and a capitalised word that does not start a sentence and
is not all capitals is a name. Every run of WINDOW words gives up to three hashes: of the words as they are, of the
words with numbers and units as slots, with names as slots too, and with capitalised words that open a sentence as names
as well. A slot's hash tells its type and how far back in the window the same value stood, so windows agree only if their
slots repeat alike (consistency inside the window). The windows of documents that occur in the benchmark are hash-joined to
its items.

An item is found in a document as `verbatim` if at least COVER of its windows are there by plain words, as `quoted` if RUN
consecutive words of it are, else as `reparameterised` if at least COVER of the windows that can be templates are there
by a template, two of them unless the item has one only, and across all of them each value of the item stands mostly for
one value of the document.

Items shorter than WINDOW words are one window of their own length; items under LEAST words (the rule of five words for
stages on shingles), null or empty ones match nothing, and nor do null or empty texts. An item_id that stands for several
texts is found if any of them is. Rows with equal doc_id and text count once. Windows with fewer than half plain words are
not used as templates and do not count towards them. Very long texts are read whole, half a megabyte of text at a time or
one text. Empty tables give no rows; extra columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C
from . import words as W

WINDOW, LEAST, COVER, AGREE, RUN = 8, 5, 0.5, 0.5, 13
SALTS, SMALL = 16, 500_000
BROADCAST_HASHES = 4_000_000
# fixed values: unit words
UNITS = (
    "mm cm dm m km inch inches ft foot feet yd yard yards mile miles mg g gr kg gram grams kilogram kilograms ton tons tonne tonnes "
    "lb lbs pound pounds oz ounce ounces ml cl l liter liters litre litres gallon gallons s sec secs second seconds min mins minute "
    "minutes h hr hrs hour hours day days week weeks month months year years km/h mph kmh percent pct degree degrees dollar dollars "
    "usd euro euros eur cent cents pound pounds gbp yen watt watts kw volt volts amp amps hz khz mhz ghz kb mb gb tb"
).split()


def _hash_of(text: str) -> np.uint64:
    raw = text.encode()
    return W.scan(np.frombuffer(raw, np.uint8), np.array([0, len(raw)])).hash[0]


_UNITS = np.unique(np.array([_hash_of(u) for u in UNITS if u.isalpha()], dtype=np.uint64))
_NUMBER, _UNIT, _NAME = (np.uint64(x) for x in (0x6A09E667F3BCC909, 0xBB67AE8584CAA73B, 0x3C6EF372FE94F82B))
_FACTORS = np.array([pow(0xA24BAED4963EE407, i + 1, 1 << 64) for i in range(WINDOW)], dtype=np.uint64)
_SPACE = W._lookup(lambda b: b in b" \t\r\x0b\x0c")
_OPENS = W._lookup(lambda b: b in b"\n.!?:;|\"'([{*-#>")


# kinds of words that are slots: none, numbers and units, names too, words that open a sentence too
FAMILIES = ((), (1, 2), (1, 2, 3), (1, 2, 3, 4))


class Tokens:
    """Words with their slot types: 0 plain, 1 number, 2 unit, 3 name, 4 capitalised word that opens a sentence."""

    def __init__(self, raw: np.ndarray, offsets: np.ndarray):
        words = W.scan(raw, offsets)
        start, end, doc, plain = words.start, words.end, words.doc, words.hash
        number = W._DIGIT[raw[start]] if len(start) else np.zeros(0, bool)
        # digits behind a point or comma belong to the number before
        joined = np.zeros(len(start), dtype=bool)
        if len(start) > 1:
            gap = (start[1:] - end[:-1] == 1) & number[1:] & number[:-1] & (doc[1:] == doc[:-1])
            mark = raw[end[:-1]] if len(raw) else np.zeros(0, np.uint8)
            joined[1:] = gap & ((mark == 0x2E) | (mark == 0x2C)) if len(mark) == len(gap) else gap
        if joined.any():
            keep = np.flatnonzero(~joined)
            group = np.cumsum(~joined) - 1
            last = np.zeros(len(keep), dtype=np.int64)
            np.maximum.at(last, group, end)
            value = np.zeros(len(keep), dtype=np.uint64)
            np.add.at(value, group, W.mix(plain + np.arange(len(plain), dtype=np.uint64) - keep[group].astype(np.uint64)))
            plain = np.where(np.bincount(group) > 1, value, plain[keep])
            start, end, doc, number = start[keep], last, doc[keep], number[keep]
        self.start, self.end, self.doc, self.plain = start, end, doc, plain
        self.first = np.searchsorted(doc, np.arange(len(offsets)))
        kind = np.zeros(len(start), dtype=np.int8)
        kind[number] = 1
        if len(start):
            after = np.concatenate([[False], number[:-1] & (doc[1:] == doc[:-1])])
            kind[after & np.isin(plain, _UNITS) & ~number] = 2
            capital, inner = self._names(raw, offsets)
            kind[capital & (kind == 0)] = 4
            kind[inner & (kind == 4)] = 3
        self.kind = kind
        # how far back the same value of a slot stood
        self.back = np.full(len(start), WINDOW, dtype=np.int64)
        slot = np.flatnonzero(kind)
        if len(slot):
            order = slot[np.lexsort((slot, plain[slot], doc[slot]))]
            same = (plain[order][1:] == plain[order][:-1]) & (doc[order][1:] == doc[order][:-1])
            self.back[order[1:][same]] = np.minimum(WINDOW, order[1:][same] - order[:-1][same])

    def _names(self, raw, offsets) -> tuple[np.ndarray, np.ndarray]:
        """(capitalised words, those of them that do not open a sentence)"""
        start, end = self.start, self.end
        head = raw[start]
        second = raw[np.minimum(start + 1, len(raw) - 1)]
        upper = W._UPPER[head] | ((head == 0xC3) & (second >= 0x80) & (second <= 0x9E))
        small = np.concatenate([[0], np.cumsum((raw >= 0x61) & (raw <= 0x7A))])
        upper &= small[end] > small[start]
        at = np.flatnonzero(upper)
        # the nearest mark before that is not a blank
        index = np.where(_SPACE[raw], 0, np.arange(1, len(raw) + 1))
        last = np.concatenate([[0], np.maximum.accumulate(index)])[start[at]] - 1
        inner = np.zeros(len(upper), dtype=bool)
        inner[at] = (last >= offsets[self.doc[at]]) & ~_OPENS[raw[np.maximum(last, 0)]]
        return upper, inner

    def windows(self, size: int):
        """(index of the first word, family, hash) of all windows of `size` words."""
        n = len(self.start) - size + 1
        if n <= 0:
            return [np.zeros(0, np.int64), np.zeros(0, np.int8), np.zeros(0, np.uint64)]
        ok = self.doc[:n] == self.doc[size - 1 :]
        typed = np.array([0, _NUMBER, _UNIT, _NAME, _NAME], dtype=np.uint64)[self.kind]
        slot_of = [np.isin(self.kind, kinds) for kinds in FAMILIES]
        counts = []
        for slot in slot_of:
            total = np.concatenate([[0], np.cumsum(slot)])
            counts.append(total[size:] - total[:-size])
        out = []
        for family, slot in enumerate(slot_of):
            # a family has the windows to which its own kind of slot adds something
            at = np.flatnonzero(ok if family == 0 else ok & (counts[family] > counts[family - 1]) & (2 * counts[family] <= size))
            if not len(at):
                continue
            total = np.full(len(at), size * 8 + family, dtype=np.uint64) * W._MUL
            for i in range(size):
                j = at + i
                token = self.plain[j]
                if family:
                    back = np.where(self.back[j] <= i, self.back[j], 0).astype(np.uint64)
                    token = np.where(slot[j], typed[j] + back * W._MUL, token)
                total += token * _FACTORS[i]
            out.append((at, np.full(len(at), family, np.int8), W.mix(total)))
        return [np.concatenate(x) for x in zip(*out)] if out else [np.zeros(0, np.int64), np.zeros(0, np.int8), np.zeros(0, np.uint64)]

    def slot_values(self, data: bytes, at: int, size: int, family: int) -> list[str]:
        return [data[self.start[j] : self.end[j]].decode("utf-8", "replace").lower() for j in range(at, at + size) if self.kind[j] in FAMILIES[family]]


def item_windows(items: list[tuple[int, str]]):
    """Rows (hash, item, family, first word, slots, size, can) of the items' windows; the first of equal windows of a family stands for all.

    can: the window is a template, or holds no slot that could change.
    """
    rows = []
    for item, text in items:
        data = (text or "").encode()
        tokens = Tokens(np.frombuffer(data, np.uint8), np.array([0, len(data)]))
        size = min(WINDOW, len(tokens.start))
        if size < LEAST:
            continue
        at, family, hashed = tokens.windows(size)
        seen = {}
        for a, f, h in zip(at.tolist(), family.tolist(), hashed.tolist()):
            seen.setdefault((f, h), a)
        for (f, h), a in seen.items():
            rows.append((h - (1 << 64) if h >> 63 else h, item, f, a, tokens.slot_values(data, a, size, f) if f else [], size, bool(f) or not tokens.kind[a : a + size].any()))
    return rows


def longest_run(places):
    """Length of the longest run of consecutive numbers in a sorted array column."""
    step = lambda s, x: F.struct(x.alias("last"), F.when(x == s["last"] + 1, s["run"] + 1).otherwise(F.lit(1)).alias("run"), F.greatest(s["best"], F.when(x == s["last"] + 1, s["run"] + 1).otherwise(F.lit(1))).alias("best"))
    start = F.struct(F.lit(-2).alias("last"), F.lit(0).alias("run"), F.lit(0).alias("best"))
    return F.aggregate(places, start, step, lambda s: s["best"])


def find(docs: DataFrame, benchmark: DataFrame, cover: float = COVER, agree: float = AGREE, run: int = RUN) -> DataFrame:
    """doc_id, node (hash of the text), item_id, kind, coverage, consistency of every item found in a document."""
    spark = docs.sparkSession

    def prepare(batches):
        for b in batches:
            rows = item_windows(list(zip(b.column("item").to_pylist(), b.column("text").to_pylist())))
            columns = list(zip(*rows)) if rows else [[]] * 7
            types = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.list_(pa.string()), pa.int32(), pa.bool_())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types)], names=["hash", "item", "family", "at", "item_slots", "size", "can"])

    # an item is a text: its hash stands for it until the end, where the ids that own it are put back
    given = benchmark.select("item_id", "text").where("item_id is not null and text is not null").withColumn("item", F.xxhash64("text"))
    owners = C.materialize(given.select("item", "item_id").distinct(), "template-owners")
    known = C.materialize(given.select("item", "text").dropDuplicates(["item"]).mapInArrow(prepare, "hash long, item long, family int, at int, item_slots array<string>, size int, can boolean"), "template-items")
    sizes = sorted(r[0] for r in known.select("size").distinct().collect())  # at most WINDOW values
    hashes = C.materialize(known.select("hash").distinct(), "template-hashes")
    parts = -(-hashes.count() // BROADCAST_HASHES)
    texts = docs.select("doc_id", "text").where("doc_id is not null and text is not null").withColumn("node", F.xxhash64("text"))
    out = "doc_id long, node long, hash long, doc_slots array<string>"
    found = None
    for part in range(parts):  # one part, unless the benchmark is very large
        own = hashes.where(F.pmod(F.col("hash"), F.lit(parts)) == part).toArrow().column(0).to_numpy()
        shared = spark.sparkContext.broadcast(np.sort(own.astype(np.int64).view(np.uint64)))

        def match(batches, shared=shared):
            known = shared.value
            coarse = np.zeros(1 << 20, dtype=bool)
            coarse[(known >> np.uint64(44)).astype(np.int64)] = True
            for b in batches:
                for piece in C.small_batches(b, "text"):
                    raw, offsets = C.text_bytes(piece.column("text"))
                    tokens = Tokens(raw, offsets)
                    data, rows = None, {}
                    for size in sizes:
                        at, family, hashed = tokens.windows(size)
                        maybe = np.flatnonzero(coarse[(hashed >> np.uint64(44)).astype(np.int64)])
                        place = np.minimum(np.searchsorted(known, hashed[maybe]), len(known) - 1)
                        for i in maybe[known[place] == hashed[maybe]].tolist():
                            f, a = int(family[i]), int(at[i])
                            if f and data is None:
                                data = raw.tobytes()
                            rows[int(tokens.doc[a]), int(hashed[i]), tuple(tokens.slot_values(data, a, size, f)) if f else ()] = None
                    if rows:
                        doc, h, slots = zip(*rows)
                        pick = pa.array(doc)
                        yield pa.RecordBatch.from_arrays([piece.column("doc_id").cast(pa.int64()).take(pick), piece.column("node").take(pick), pa.array(np.array(h, dtype=np.uint64).view(np.int64)), pa.array([list(s) for s in slots], pa.list_(pa.string()))], names=["doc_id", "node", "hash", "doc_slots"])

        own_found = texts.mapInArrow(match, out)
        found = own_found if found is None else found.unionByName(own_found)
    if found is None:
        return texts.where("false").select("doc_id", "node", F.lit(0).cast("long").alias("item_id"), F.lit("").alias("kind"), F.lit(0.0).alias("coverage"), F.lit(0.0).alias("consistency"))
    places = lambda when: F.count_distinct(F.when(when, F.col("at")))
    totals = known.groupBy("item").agg(places(F.col("family") == 0).alias("windows"), places(F.col("can")).alias("templates"), F.max("size").alias("size"))
    known = known.drop("size", "can")
    if known.count() <= SMALL:
        joined = found.join(F.broadcast(known), "hash")
    else:  # a passage that very many documents share is spread over SALTS keys
        salted = known.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        joined = found.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)).cast("int")).join(salted, ["hash", "salt"]).drop("salt")
    pairs = C.materialize(joined.distinct(), "template-pairs")
    key = ["doc_id", "node", "item"]
    # a template covers a window by its own hash, or by the plain one where the words agree outright
    per_item = pairs.groupBy(*key).agg(
        F.sort_array(F.collect_set(F.when(F.col("family") == 0, F.col("at")))).alias("places"), F.count_distinct("at").alias("any")
    ).select(*key, F.size("places").alias("plain"), longest_run(F.col("places")).alias("run"), "any").join(totals, "item")
    votes = (
        pairs.where("family > 0").select(*key, F.explode(F.arrays_zip("item_slots", "doc_slots")).alias("s"))
        .groupBy(*key, F.col("s.item_slots").alias("a"), F.col("s.doc_slots").alias("b")).agg(F.count("*").alias("n"))
        .groupBy(*key, "a").agg(F.max("n").alias("most"), F.sum("n").alias("n"))
        .groupBy(*key).agg((F.sum("most") / F.sum("n")).alias("consistency"))
    )
    scored = per_item.join(votes, key, "left").withColumn("consistency", F.coalesce("consistency", F.lit(1.0)))
    verbatim = F.col("plain") >= cover * F.col("windows")
    quoted = (F.col("run") > 0) & (F.col("run") + F.col("size") - 1 >= run)
    template = (F.col("any") >= cover * F.col("templates")) & (F.col("any") >= F.least(F.lit(2), F.col("templates"))) & (F.col("consistency") >= agree)
    kind = F.when(verbatim, "verbatim").when(quoted, "quoted").when(template, "reparameterised")
    share = F.when(verbatim | quoted, F.col("plain") / F.col("windows")).otherwise(F.col("any") / F.col("templates"))
    judged = scored.select(*key, kind.alias("kind"), F.least(F.lit(1.0), share).alias("coverage"), "consistency").where("kind is not null")
    # of the texts of an item_id the best covered one is reported
    best = F.max(F.struct("coverage", "kind", "consistency")).alias("best")
    return judged.join(F.broadcast(owners) if owners.count() <= SMALL else owners, "item").groupBy("doc_id", "node", "item_id").agg(best).select(
        "doc_id", "node", "item_id", "best.kind", "best.coverage", "best.consistency")


def drop_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """docs without the rows in which an item is found; all columns stay as they are."""
    gone = C.materialize(find(docs, benchmark).select("doc_id", "node").distinct(), "template-gone")
    if gone.count() <= BROADCAST_HASHES:
        gone = F.broadcast(gone)
    gone = gone.select(F.col("doc_id").alias("gone_doc_id__"), F.col("node").alias("gone_node__"))
    return docs.join(gone, (F.xxhash64(docs["text"]) == F.col("gone_node__")) & (docs["doc_id"] == F.col("gone_doc_id__")), "left_anti")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find(C.table(spark, sf_dir, "documents"), C.table(spark, sf_dir, "benchmark")).drop("node")
