"""Benchmark decontamination by template canonicalisation.

Tokens are lower-cased words without outer punctuation; numbers, units after or glued to a number and names (capitalised words inside a
sentence) become typed placeholders whose values are kept. A sentence's first word is read both as a word and, unless it is a common first
word, as a name. Windows of ``width`` template tokens hash-join the benchmark's
windows; a hit survives if its slots are consistent: within it, a slot value of the item maps to one value of the document, so a
question with other numbers is caught and an unrelated sentence of the same frame with scrambled slots is not. A document is contaminated by an item if the item's words covered by its consistent hits reach
``share`` of the item, or ``run`` words in one stretch; items shorter than a window match as a whole.

One way for benchmarks of any size: windows of documents whose hash is not in a bit map of the benchmark's hashes (of a fixed size, so
that it can be broadcast) are left out; the others are joined by hash and template, with the values of their slots alone, and each pair of windows is judged by
itself. Hits are gathered per text and item, so that a group of copies is judged once, and meet the rows again by a hash of
the text. Nothing but a window's tokens travels.

Edge cases: null and empty texts have no window and are kept; items without words match nothing; repeated items count once; an item
without an id is reported as null among ``items``, after the others; items that share an id are judged one by one; rows of ``docs`` keep all their columns,
repeated rows stay, and rows that share a doc_id, or have none, are judged by their own texts; windows of placeholders alone say nothing of a question and are not compared."""

from __future__ import annotations

import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common as C

#: A number between outer punctuation, with a unit that may be glued to it.
NUMBER = re.compile(r"[\W_]*?([+-]?[$€£]?(?:(?<![\W_])\.)?\d(?:[\d.,:/]*\d)?%?)(?:-?([^\W\d_]+[²³]?(?:/[^\W\d_]+[²³]?)?))?[\W_]*")
#: Units that follow a number (fixed list).
UNITS = frozenset(
    """km kilometer kilometers kilometre kilometres m meter meters metre metres cm centimeter centimeters centimetre centimetres mm millimeter millimeters millimetre
    millimetres mi mile miles ft foot feet inch inches yd yard yards acre acres hectare hectares ha kg kilogram kilograms kilo kilos g gram grams mg milligram milligrams
    t ton tons tonne tonnes oz ounce ounces lb lbs pound pounds l liter liters litre litres ml milliliter milliliters millilitre millilitres gal gallon gallons pint pints
    quart quarts cup cups teaspoon teaspoons tablespoon tablespoons ms millisecond milliseconds s sec secs second seconds min mins minute minutes h hr hrs hour hours
    day days week weeks month months yr yrs year years decade decades century centuries dollar dollars cent cents euro euros pence penny pennies usd eur gbp percent degree degrees
    radian radians celsius fahrenheit kelvin mph kmh kph km/h m/s ft/s m² m³ km² cm² cm³ hz khz mhz ghz w kw mw kwh watt watts kilowatt kilowatts v volt volts amp amps ampere
    amperes ohm ohms j kj joule joules cal kcal calorie calories n newton newtons pa kpa pascal pascals mol mole moles bit bits byte bytes kb mb gb tb""".split()
)
#: Words that begin a sentence with a capital and are no names (fixed list).
STARTERS = frozenset(
    """a about after all also although an and another any are as assume at be because before both but by calculate can compute consider could determine did do does during each
    either estimate evaluate every explain express few find first for four from given had has have he her here his how however i if in into is it its last let many more most my next no
    not now of on once one or other our over she show simplify since so solve some state still suppose ten that the their then there these they this those three to two under until
    use was we were what when where whether which while who whom whose why will with without would write you your""".split()
)
#: Bits of the map of the benchmark's window hashes; texts with marks, or windows of items (of some 200 bytes each), that may be broadcast, beyond which they are
#: shuffled to the same join.
BITS, MOST_TEXTS = 26, 100_000
_OUTER = re.compile(r"^[\W_]+|[\W_]+$")


#: How a word is written: plain and within a sentence, plain and ending one, a number, like a name, without letters and digits.
PLAIN, LAST, DIGITS, CAPITAL, BLANK = range(5)


def _read(raw: str) -> tuple[int, str, bool, str | None]:
    """How a word is written; it without outer punctuation in lower case; whether it ends a sentence; the unit glued to it."""
    bare = raw if raw[-1].isalpha() else raw[:-1]
    if bare.isalpha() and (bare is raw or raw[-1] in ".,;:!?"):  # letters alone, but for one mark: no number
        ends = bare is not raw and raw[-1] in ".!?:"
        return CAPITAL if bare[0].isupper() and not bare.isupper() else LAST if ends else PLAIN, bare.lower(), ends, None
    m = NUMBER.fullmatch(raw)
    unit = m and m[2] and m[2].lower()
    ends = raw[-1] in ".!?:"
    if m is not None and (unit is None or unit in UNITS):
        return DIGITS, m[1].lower(), ends, unit
    bare = _OUTER.sub("", raw)
    return BLANK if not bare else CAPITAL if bare[0].isupper() and not bare.isupper() else LAST if ends else PLAIN, bare.lower(), ends, None


_token_hash = C.task_memo(lambda t: C.word_hash.fn(t.encode()))
_known = C.task_memo(lambda raw: (*(r := _read(raw)), C.word_hash.fn(r[1].encode())))


def template(text: bytes | None) -> tuple[list[str], list[str], list[int]]:
    """Template tokens, the values behind them (the token itself where there is no slot), and where a sentence begins with what may be a name."""
    return hashed_template(text)[:3]


def hashed_template(text: bytes | None) -> tuple[list[str], list[str], list[int], np.ndarray]:
    """``template`` and the hashes of its tokens, which are known with the words."""
    values, slots, initial, found, start, after = [], [], [], [], True, False
    add, note = values.append, found.append
    for kind, low, ends, unit, h in map(_known.__getitem__, (text or b"").decode("utf-8", "replace").split()):
        if not kind and not after:
            add(low)
            note(h)
            start = False
            continue
        if kind != BLANK:
            if kind == DIGITS:
                slots.append((len(values), "<number>"))
                if unit:
                    add(low)
                    note(h)
                    slots.append((len(values), "<unit>"))
                    low = unit
            elif after and low in UNITS:
                slots.append((len(values), "<unit>"))
            elif kind == CAPITAL and not start:
                slots.append((len(values), "<name>"))
            elif kind == CAPITAL and low not in STARTERS:
                initial.append(len(values))
            add(low)
            note(h)
            after = kind == DIGITS and not unit
        start = ends
    tokens, hs = values.copy(), np.array(found, C.U64)
    for k, slot in slots:
        tokens[k] = slot
        hs[k] = _SLOT[slot]
    return tokens, values, initial, hs


_SLOT = {t: C.U64(_token_hash[t]) for t in ("<number>", "<unit>", "<name>")}
_NUMBER, _UNIT, _NAME = np.array([_token_hash[t] for t in ("<number>", "<unit>", "<name>")], C.U64)


def hashes(tokens: list[str]) -> np.ndarray:
    return np.fromiter(map(_token_hash.__getitem__, tokens), C.U64, len(tokens))


def windows(h: np.ndarray, width: int) -> np.ndarray:
    """Template hash of each window of token hashes; 0 where a window is placeholders alone."""
    if len(h) < width:
        width = len(h)
    if not width:
        return np.empty(0, C.U64)
    out = C.rolling(h, width)
    slot = (h == _NUMBER) | (h == _UNIT) | (h == _NAME)
    if slot.sum() < width:
        return out
    full = np.concatenate(([0], np.cumsum(slot)))
    return np.where(full[width:] - full[:-width] == width, C.U64(0), out)


def readings(tokens: list[str], initial: list[int], h: np.ndarray | None = None) -> list[tuple[list[str], np.ndarray]]:
    """Tokens and their hashes with the first words of sentences as words, and as names where that differs."""
    out = [(tokens, hashes(tokens) if h is None else h)]
    if initial:
        named, h = tokens.copy(), out[0][1].copy()
        for k in initial:
            named[k] = "<name>"
        h[initial] = _NAME
        out.append((named, h))
    return out


def consistent(item: list[str], item_at: int, doc: list[str], doc_at: int, slots: list[str], n: int) -> bool:
    """Each slot value of the item has one value in the document's window; the new question may set two of them equal."""
    there = {}
    for k in range(n):
        if slots[item_at + k][0] == "<":
            a, b = item[item_at + k], doc[doc_at + k]
            if there.setdefault((slots[item_at + k], a), b) != b:
                return False
    return True


def consistent_values(slots: str, item: str, doc: str) -> bool:
    """``consistent`` for whole windows, tokens joined by spaces."""
    t = slots.split(" ")
    return consistent(item.split(" "), 0, doc.split(" "), 0, t, len(t))


def found_windows(tokens: list[str], values: list[str], initial: list[int], widths: list[int], keep, known: np.ndarray | None = None) -> list[tuple[int, int, str, str]]:
    """(start, hash, template, values) of the windows of ``widths`` tokens, in both readings, whose hashes ``keep`` lets pass."""
    out = []
    for k, (mine, h) in enumerate(readings(tokens, initial, known)):
        for n in widths:
            if len(tokens) < n:
                continue
            w = windows(h, n)
            for d in np.flatnonzero(keep(w)).tolist():
                t = " ".join(mine[d : d + n])
                if not k or t != " ".join(tokens[d : d + n]):  # the second reading where it differs
                    out.append((d, int(w[d : d + 1].view(np.int64)[0]), t, " ".join(values[d : d + n])))
    return out


_WINDOWS = "start int, h long, slots string, said string"


def _item_windows(width: int):
    def run(batches):
        for batch in batches:
            rows = []
            for key, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                tokens, values, initial = template(t)
                if tokens:
                    rows += [(key, len(tokens), *w) for w in found_windows(tokens, values, initial, [min(width, len(tokens))], lambda w: w != 0)]
            c = list(zip(*rows)) or [[]] * 6
            types = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.string(), pa.string())
            yield pa.record_batch([pa.array(x, t) for x, t in zip(c, types)], names=["item", "size", "start", "h", "slots", "said"])

    return run


def _text_windows(shared, widths: list[int]):
    """Windows of texts that may be the benchmark's, with the text's two hashes."""

    def run(batches):
        bits = np.frombuffer(zlib.decompress(shared.value), np.uint8)

        def keep(w):
            at = w >> C.U64(64 - BITS)
            return (bits[(at >> C.U64(3)).view(np.int64)] >> (at & C.U64(7)).astype(np.uint8) & 1).astype(bool) & (w != 0)

        for batch in batches:
            k1, k2 = (batch.column(i).to_pylist() for i in (1, 2))
            rows = []
            for a, b, t in zip(k1, k2, C.texts(batch)):
                if t:
                    *read, known = hashed_template(t)
                    rows += [(a, b, *w) for w in found_windows(*read, widths, keep, known)]
            c = list(zip(*rows)) or [[]] * 6
            types = (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.string(), pa.string())
            yield pa.record_batch([pa.array(x, t) for x, t in zip(c, types)], names=["k1", "k2", "at", "h", "slots", "read"])

    return run


def _consistent(batches):
    """Joined windows with consistent slots."""
    memo = C.Memo(lambda x: consistent_values(*x), 100_000)
    for batch in batches:
        ok = [memo[x] for x in zip(*(batch.column(i).to_pylist() for i in (0, 1, 2)))]
        yield batch.filter(pa.array(ok, pa.bool_())).select(["k1", "k2", "item", "size", "start", "n"])


def _enough(share: float, run: int):
    def go(batches):
        for batch in batches:
            ok = []
            for size, starts in zip(batch.column(3).to_pylist(), batch.column(4).to_pylist()):
                cover = {i for x in starts for i in range(x["start"], x["start"] + x["n"])}
                ok.append(len(cover) >= share * size or _longest(cover) >= run)
            yield batch.filter(pa.array(ok, pa.bool_())).select(["k1", "k2", "item"])

    return go


def _longest(cover: set[int]) -> int:
    best = size = 0
    for x in sorted(cover):
        size = size + 1 if x - 1 in cover else 1
        best = max(best, size)
    return best


def text_keys() -> list[Column]:
    """128 bits that stand for a text."""
    return [F.xxhash64("text").alias("k1"), F.xxhash64(F.lit(1), "text").alias("k2")]


def _marked(docs: DataFrame, benchmark: DataFrame, width: int = 8, share: float = 0.6, run: int = 13) -> DataFrame:
    """(_rest, items): whole rows of ``docs`` and the ids of what contaminates them."""
    spark = docs.sparkSession
    bench = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("text is not null").distinct()
    bench = C.cut(bench.withColumn("item", F.monotonically_increasing_id()))
    own = C.cut(bench.select("item", F.col("text").cast("binary").alias("text")).mapInArrow(C.task(_item_windows(width)), f"item long, size int, {_WINDOWS}"))
    widths = sorted(r.n for r in own.select(F.least("size", F.lit(width)).alias("n")).distinct().collect())  # at most ``width`` values
    hashes_ = own.select((F.shiftrightunsigned("h", 64 - BITS) + 1).alias("bit"))
    shared = spark.sparkContext.broadcast(zlib.compress(C.bitmap(hashes_, BITS), 1))  # 2**BITS bits, mostly zeros, whatever the benchmark's size
    src = docs.select(F.col("text").cast("string").alias("text")).where("text is not null").select("text", *text_keys())
    found = src.mapInArrow(C.task(_text_windows(shared, widths)), "k1 long, k2 long, at int, h long, slots string, read string")
    # what a window says meets the items once, whatever the number of texts and places that have it
    pairs = found.select("k1", "k2", "h", "slots", "read").distinct().join(F.broadcast(own) if own.limit(MOST_TEXTS + 1).count() <= MOST_TEXTS else own, ["h", "slots"])
    n = F.least("size", F.lit(width)).alias("n")
    hits = pairs.select("slots", "said", "read", "k1", "k2", "item", "size", "start", n).mapInArrow(C.task(_consistent), "k1 long, k2 long, item long, size int, start int, n int")
    per = hits.groupBy("k1", "k2", "item", "size").agg(F.collect_set(F.struct("start", "n")).alias("starts"))  # at most an item's windows
    bad = per.mapInArrow(C.task(_enough(share, run)), "k1 long, k2 long, item long").join(bench.select("item", "item_id"), "item")
    bad = bad.groupBy("k1", "k2").agg(F.collect_set("item_id").alias("known"), F.max(F.col("item_id").isNull()).alias("none"))
    bad = C.cut(bad.select("k1", "k2", F.concat(F.array_sort("known"), F.when(F.col("none"), F.array(F.lit(None).cast("long"))).otherwise(F.array().cast("array<bigint>"))).alias("items")))
    keyed = docs.select(F.struct(*docs.columns).alias("_rest"), F.col("text").cast("string").alias("text")).select("_rest", *text_keys())
    few = F.broadcast(bad) if bad.limit(MOST_TEXTS + 1).count() <= MOST_TEXTS else bad
    return keyed.join(few, ["k1", "k2"], "left").select("_rest", F.coalesce("items", F.array().cast("array<bigint>")).alias("items"))


def mark(docs: DataFrame, benchmark: DataFrame, **how) -> DataFrame:
    """All columns of ``docs`` and ``items``, the sorted ids of the contaminating items (empty if clean), in place of a column of that name."""
    return _marked(docs, benchmark, **how).select(*(F.col(f"_rest.`{c}`") for c in docs.columns if c != "items"), "items")


def clean(docs: DataFrame, benchmark: DataFrame, **how) -> DataFrame:
    """The rows of ``docs``, all columns, that no item contaminates."""
    return _marked(docs, benchmark, **how).where(F.size("items") == 0).select(*(F.col(f"_rest.`{c}`") for c in docs.columns))


def op8_decontaminate(spark, sf_dir: str) -> DataFrame:
    docs = C.table(spark, sf_dir, "documents").select("doc_id", "text")
    out = mark(docs, C.table(spark, sf_dir, "benchmark"))
    return out.select("doc_id", "items", (F.size("items") > 0).alias("contaminated"))
