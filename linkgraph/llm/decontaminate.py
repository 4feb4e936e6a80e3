"""Benchmark decontamination by template canonicalisation.

Numbers, names and units are replaced by typed placeholders, and the windows of
the resulting templates are joined by hash: those of the items with those of the
documents.  Where a window of an item is found in a document, both are aligned
token by token: literal tokens must be equal, and a slot counts only if the
item's value maps to one value of the document throughout.  So a question with
other numbers or names is caught, and text that merely has the same shape is
not.  Items without a window of enough literal words are looked up as a whole,
by their values and by their template; there all tokens must agree.

Texts are tokenised on UTF-8 bytes, many rows at a time.  Before the join, a bit
table of fixed size keeps back the windows of documents that no item can have.
Neither the benchmark nor its windows are collected: pairs of document and item
are verified one by one.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkgraph.llm.common import as_long, materialise, mix, only_possible, powers, row_slices, text_bytes

LITERAL, NUMBER, NAME, UNIT = range(4)

#: Units that count as such after a number.
UNITS = (
    "mm", "cm", "m", "km", "in", "ft", "yd", "mi", "inch", "inches", "feet", "foot", "yards", "miles", "meters", "metres", "kilometers", "kilometres", "mg", "g", "kg", "lb", "lbs", "oz", "t", "tons",
    "grams", "kilograms", "pounds", "ml", "l", "dl", "liters", "litres", "gallons", "s", "sec", "seconds", "min", "minutes", "h", "hr", "hours", "days", "weeks", "months", "years", "kmh", "mph", "hz",
    "w", "kw", "v", "j", "pa", "usd", "eur", "dollars", "euros", "cents", "percent", "degrees",
)


@dataclass(frozen=True)
class DecontaminationParams:
    #: Template tokens in a window, and how many of them must be literal.
    width: int = 8
    literal_least: int = 4
    #: Items with fewer tokens are too short to be recognised within a text; they are found as whole rows.
    item_least: int = 4
    #: Share of an item's tokens that a document must hold in line.
    share_least: float = 0.5
    #: Bits of the table that keeps windows out of the join (bounded size).
    filter_bits: int = 24


_DIGIT = np.zeros(256, bool)
_DIGIT[0x30:0x3A] = True
_UPPER = np.zeros(256, bool)
_UPPER[0x41:0x5B] = True
_SMALL = np.zeros(256, bool)
_SMALL[0x61:0x7B] = True
_WORD = _DIGIT | _UPPER | _SMALL
_WORD[0x80:] = True
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_STOP = np.zeros(256, bool)
_STOP[[ord(c) for c in ".!?:;"]] = True
_POINT = np.zeros(256, bool)
_POINT[[0x2C, 0x2E]] = True


def _hash_runs(block: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    """Hashes of the byte runs [first, last) of lower-cased ``block``."""
    length = last - first
    total = int(length.sum())
    at = np.cumsum(length) - length
    place = np.arange(total) - np.repeat(at, length)
    letters = block[np.repeat(first, length) + place].astype(np.uint64) + np.uint64(1)
    letters *= powers(int(length.max()) if len(length) else 1)[place]
    sums = np.add.reduceat(letters, at) if len(at) else np.zeros(0, np.uint64)
    return mix(sums + length.astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F))


_UNIT_HASHES = np.sort(np.array([_hash_runs(np.frombuffer(u.encode(), np.uint8), np.array([0]), np.array([len(u)]))[0] for u in UNITS]))
_SLOT_HASHES = mix(np.array([0, 11, 12, 13], np.uint64))


@dataclass
class Tokens:
    #: Template hash, value hash and kind of each token, and tokens a row.
    template: np.ndarray
    value: np.ndarray
    kind: np.ndarray
    rows: np.ndarray


def template_tokens(data: np.ndarray, offsets: np.ndarray) -> Tokens:
    lo, hi = int(offsets[0]), int(offsets[-1])
    raw = data[lo:hi]
    ends = offsets - lo
    n = len(raw)
    if not n:
        return Tokens(*(np.zeros(0, np.uint64),) * 2, np.zeros(0, np.int8), np.zeros(len(offsets) - 1, np.int64))
    edge = np.zeros(n + 1, bool)
    edge[ends] = True
    inside = _WORD[raw]
    digit = _DIGIT[raw]
    between = _POINT[raw]
    between[0] = between[-1] = False
    between[1:-1] &= digit[:-2] & digit[2:]
    between &= ~edge[:-1] & ~edge[1:]
    inside |= between
    begins = inside.copy()
    begins[1:] &= ~inside[:-1] | edge[1:-1]
    stops = inside.copy()
    stops[:-1] &= ~inside[1:] | edge[1:-1]
    first, last = np.flatnonzero(begins), np.flatnonzero(stops) + 1
    rows = np.diff(np.searchsorted(first, ends))
    low = raw.copy()
    low[_UPPER[raw]] += 32
    accent = np.zeros(n, bool)
    accent[1:] = (raw[:-1] == 0xC3) & (raw[1:] >= 0x80) & (raw[1:] <= 0x9E) & (raw[1:] != 0x97)
    low[accent] += 32
    value = _hash_runs(low, first, last)
    kind = np.zeros(len(first), np.int8)
    kind[digit[first]] = NUMBER
    # a name begins with a capital, goes on in small letters and starts no sentence
    last_seen = np.maximum.accumulate(np.where(_SPACE[raw], -1, np.arange(n)))
    prior = np.where(first > 0, last_seen[np.maximum(first - 1, 0)], -1)
    row_start = np.repeat(ends[:-1], rows)
    opens = (prior < row_start) | _STOP[raw[np.maximum(prior, 0)]]
    second = np.minimum(first + 1, n - 1)
    capital = _UPPER[raw[first]] & (last - first > 1) & _SMALL[raw[second]]
    kind[capital & ~opens] = NAME
    after_number = np.zeros(len(first), bool)
    after_number[1:] = (kind[:-1] == NUMBER) & (first[1:] != row_start[1:])
    found = np.minimum(np.searchsorted(_UNIT_HASHES, value), len(_UNIT_HASHES) - 1)
    kind[after_number & (_UNIT_HASHES[found] == value)] = UNIT
    template = np.where(kind == LITERAL, value, _SLOT_HASHES[kind])
    return Tokens(template, value, kind, rows)


def windows(tokens: Tokens, width: int, literal_least: int) -> tuple[np.ndarray, np.ndarray]:
    """First token and hash of every window within a row with enough literals."""
    n = len(tokens.template)
    if n < width:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    coef = mix(np.arange(7001, 7001 + width, dtype=np.uint64)) | np.uint64(1)
    total = np.zeros(n - width + 1, np.uint64)
    for k in range(width):
        total += tokens.template[k : n - width + 1 + k] * coef[k]
    row = np.repeat(np.arange(len(tokens.rows)), tokens.rows)
    literal = np.append(0, np.cumsum(tokens.kind == LITERAL))
    good = (row[: n - width + 1] == row[width - 1 :]) & (literal[width:] - literal[:-width] >= literal_least)
    at = np.flatnonzero(good)
    return at, mix(total[at] + np.uint64(width))


def whole_runs(codes: np.ndarray, rows: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """First token and hash of every run of ``width`` codes within a row, whatever they are."""
    n = len(codes)
    if n < width:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    total = np.append(np.uint64(0), np.cumsum(codes * powers(n)[:n], dtype=np.uint64))
    row = np.repeat(np.arange(len(rows)), rows)
    at = np.flatnonzero(row[: n - width + 1] == row[width - 1 :])
    return at, mix((total[at + width] - total[at]) * powers(n, "down")[at] + np.uint64(width))


#: What a key of an item or a document stands for.
WINDOW, VALUES, TEMPLATE = range(3)


def _key(hashes: np.ndarray, mode: int, width: int) -> np.ndarray:
    return mix(hashes * np.uint64(3) + np.uint64(mode * 1_000_003 + width))


def item_keys(tokens: Tokens, params: DecontaminationParams) -> Iterator[tuple[int, int, int, int]]:
    """Mode, width, key and place of the first token of each key of an item."""
    size = len(tokens.kind)
    safe = False
    if size >= params.item_least:
        width = min(size, params.width)
        least = min(params.literal_least, width - 1)
        at, value = windows(tokens, width, least)
        for p, k in zip(at, _key(value, WINDOW, width), strict=True):
            safe |= bool(p)
            yield WINDOW, width, int(k), int(p)
        if tokens.kind[0] == LITERAL:  # the first word may be taken for a name where no sentence begins
            other = Tokens(tokens.template.copy(), tokens.value, tokens.kind.copy(), tokens.rows)
            other.template[0], other.kind[0] = _SLOT_HASHES[NAME], NAME
            at, value = windows(other, width, least)
            for k in _key(value[at == 0], WINDOW, width):
                yield WINDOW, width, int(k), 0
    if not size or safe:
        return
    # windows may miss short items, and those whose only window has the first word
    rows = np.array([size])
    yield VALUES, size, int(_key(whole_runs(tokens.value, rows, size)[1], VALUES, size)[0]), 0
    literal = tokens.kind == LITERAL
    if size >= params.item_least and literal.any():
        yield TEMPLATE, size, int(_key(whole_runs(tokens.template, rows, size)[1], TEMPLATE, size)[0]), 0
        if literal[0] and literal[1:].any():
            named = np.append(_SLOT_HASHES[NAME], tokens.template[1:])
            yield TEMPLATE, size, int(_key(whole_runs(named, rows, size)[1], TEMPLATE, size)[0]), 0


def _item_keys(params: DecontaminationParams):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, kinds = ["iid", "mode", "width", "key", "at"], [pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int32()]
        for batch in batches:
            data, offsets = text_bytes(batch.column("text"))
            for r, iid in enumerate(batch.column("iid").to_pylist()):
                rows = list(item_keys(template_tokens(data, offsets[r : r + 2]), params))
                mode, width, key, at = zip(*rows, strict=True) if rows else ((),) * 4
                key = np.array(key, np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(([iid] * len(rows), mode, width, key, at), kinds, strict=True)], names=names)

    return run


def _doc_keys(params: DecontaminationParams, widths: list[tuple[int, int]], bits: np.ndarray):
    """Keys of the documents' windows that the bit table lets through, with their places."""
    mask = np.uint64((1 << params.filter_bits) - 1)

    def keys_of(tokens: Tokens) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for mode, width in widths:
            if mode == WINDOW:
                at, value = windows(tokens, width, min(params.literal_least, width - 1))
            else:
                at, value = whole_runs(tokens.value if mode == VALUES else tokens.template, tokens.rows, width)
            key = _key(value, mode, width)
            slot = key & mask
            some = (bits[(slot >> np.uint64(6)).astype(np.int64)] >> (slot & np.uint64(63))) & np.uint64(1) == 1
            yield at[some], key[some]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = text_bytes(batch.column("text"))
            ids = batch.column("rid").to_numpy()
            for lo, hi in row_slices(offsets, 1 << 20):
                tokens = template_tokens(data, offsets[lo : hi + 1])
                ends = np.cumsum(tokens.rows)
                for at, key in keys_of(tokens):
                    if len(at):
                        row = np.searchsorted(ends, at, side="right")
                        place = at - (ends - tokens.rows)[row]
                        yield pa.RecordBatch.from_arrays([pa.array(ids[lo + row]), pa.array(as_long(key)), pa.array(place.astype(np.int32))], names=["rid", "key", "place"])

    return run


def in_line(item: Tokens, doc: Tokens, shift: int) -> np.ndarray:
    """Tokens of the item that the document holds at this shift, slots being consistent."""
    a, b = max(0, -shift), min(len(item.kind), len(doc.kind) - shift)
    mine, theirs = slice(a, b), slice(a + shift, b + shift)
    kind = item.kind[mine]
    equal = (item.template[mine] == doc.template[theirs]) & (kind == doc.kind[theirs])
    equal |= (kind == LITERAL) & (item.value[mine] == doc.value[theirs])
    maps: dict[tuple[int, int], int] = {}
    for k in np.flatnonzero(equal & (kind != LITERAL)):
        value = int(doc.value[theirs.start + k])
        if maps.setdefault((int(kind[k]), int(item.value[a + k])), value) != value:
            equal[k] = False
    return np.flatnonzero(equal) + a


def share_of(item: Tokens, doc: Tokens, lines: list[tuple[int, int]], params: DecontaminationParams) -> float:
    """Share of an item found in a document, given (mode, shift) of its keys; 0 below the least share."""
    size, held = len(item.kind), set()
    for mode, shift in lines:
        if mode == WINDOW:
            held.update(in_line(item, doc, shift).tolist())
        elif mode == VALUES:
            # shorter items count only where they are the whole row
            whole = 0 <= shift <= len(doc.value) - size and bool((item.value == doc.value[shift : shift + size]).all())
            if whole and (size >= params.item_least or len(doc.kind) == size):
                return 1.0
        else:
            good = in_line(item, doc, shift)
            if len(good) == size or (len(good) == size - 1 and good[0] == 1):
                return 1.0
    share = len(held) / size if size else 0.0
    return share if share >= params.share_least else 0.0


def _verified(params: DecontaminationParams):
    """Pairs of a document and an item, ordered by document, to the share found."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, doc = None, None
        items: dict[int, Tokens] = {}
        for batch in batches:
            texts, ends = text_bytes(batch.column("text"))
            asked, asked_ends = text_bytes(batch.column("item"))
            rids, iids = batch.column("rid").to_pylist(), batch.column("iid").to_pylist()
            shares = []
            for r, lines in enumerate(batch.column("lines").to_pylist()):
                if held != rids[r]:
                    held, doc = rids[r], template_tokens(texts, ends[r : r + 2])
                if iids[r] not in items:
                    if len(items) >= 1000:
                        items.clear()
                    items[iids[r]] = template_tokens(asked, asked_ends[r : r + 2])
                shares.append(share_of(items[iids[r]], doc, [(x["mode"], x["shift"]) for x in lines], params))
            yield pa.RecordBatch.from_arrays([batch.column("rid"), batch.column("item_id"), pa.array(shares, pa.float64())], names=["rid", "item_id", "share"])

    return run


def _bit_table(index: DataFrame, bits: int) -> np.ndarray:
    """Which low bits of keys occur: ``2**bits`` bits, however many the keys."""
    slot = F.expr(f"key & {(1 << bits) - 1}L")
    words = index.select(slot.alias("b")).groupBy(F.expr("shiftright(b, 6)").alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(b & 63L as int))")).alias("mask"))
    table = np.zeros(1 << (bits - 6), np.int64)
    for word, mask in words.collect():
        table[word] = mask
    return table.view(np.uint64)


def found_items(docs: DataFrame, benchmark: DataFrame, params: DecontaminationParams = DecontaminationParams()) -> DataFrame:
    """``(rid, item_id, share)``: the items that a row of ``docs`` (rid, text) holds."""
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.coalesce("text", F.lit("")).alias("item")).filter("item_id is not null").distinct()
    items = items.withColumn("iid", F.xxhash64("item_id", "item"))
    index = materialise(items.select("iid", F.col("item").alias("text")).mapInArrow(_item_keys(params), "iid long, mode int, width int, key long, at int"), "item_keys")
    # as many as windows have widths, and lengths those items that have no window
    widths = [(r[0], r[1]) for r in index.select("mode", "width").distinct().orderBy("mode", "width").collect()]
    keys = docs.mapInArrow(_doc_keys(params, widths, _bit_table(index, params.filter_bits)), "rid long, key long, place int")
    met = keys.join(index.select("iid", "mode", "key", "at").distinct(), "key").select("rid", "iid", F.struct("mode", (F.col("place") - F.col("at")).alias("shift")).alias("line")).distinct()
    pairs = materialise(met.groupBy("rid", "iid").agg(F.collect_list("line").alias("lines")), "item_pairs")
    texts = only_possible(docs, pairs.select("rid"), params.filter_bits).dropDuplicates(["rid"])
    both = pairs.join(items, "iid").join(texts, "rid").select("rid", "iid", "item_id", "lines", "item", "text").sortWithinPartitions("rid")
    return both.mapInArrow(_verified(params), "rid long, item_id long, share double").filter("share > 0")


def contamination(docs: DataFrame, benchmark: DataFrame, params: DecontaminationParams = DecontaminationParams()) -> DataFrame:
    """doc_id, contaminated, n_items, best_share, items for every row of ``docs``.

    ``items`` lists the found item ids, joined by commas in order.  Null or
    empty texts hold nothing; an empty benchmark contaminates nothing; repeated
    items are found once; rows that repeat a doc_id, null ones included, are
    judged each by its own text.  Other columns are ignored.
    """
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("rid", F.xxhash64("doc_id", "text"))
    found = found_items(keyed.select("rid", "text"), benchmark, params).groupBy("rid").agg(F.array_sort(F.collect_set("item_id")).alias("items"), F.max("share").alias("share"))
    out = keyed.select("doc_id", "rid").join(found, "rid", "left")
    return out.select(
        "doc_id",
        F.col("items").isNotNull().alias("contaminated"),
        F.coalesce(F.size("items"), F.lit(0)).cast("long").alias("n_items"),
        F.round(F.coalesce("share", F.lit(0.0)), 6).alias("best_share"),
        F.array_join(F.coalesce("items", F.expr("cast(array() as array<long>)")).cast("array<string>"), ",").alias("items"),
    )


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, params: DecontaminationParams = DecontaminationParams()) -> DataFrame:
    """``docs`` without the rows that hold an item of the benchmark; other columns stay."""
    rid = F.xxhash64(F.col("doc_id").cast("long"), F.coalesce("text", F.lit("")))
    bad = found_items(docs.select(rid.alias("rid"), "text"), benchmark, params).select(F.col("rid").alias("_found")).distinct()
    return docs.join(bad, rid == F.col("_found"), "left_anti")


def op10_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Items of ``benchmark`` in the whole of ``documents``."""
    return contamination(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
