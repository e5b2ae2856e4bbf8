"""Quality rules with n-gram perplexity.

A modified Kneser-Ney model of ORDER-grams over the bytes of UTF-8, so of any script and with as many
n-grams as the corpus has. Each language has two, one from each half of its distinct texts (a hash
deals them), and a text is scored by the one that it had no part in. Texts that fail the base rules or
have more than a symbol for every ten words teach no model, else junk of one kind makes itself likely.
Spark counts n-grams over whole texts, sums lower orders and contexts by joins of its own, and
stores sorted arrays: 64-bit hashes, one to one, of n-grams with their discounted counts and of contexts
with their totals and back-off weights, in blocks of a hash range. Tasks read the blocks from the
shared folder; a model with more than ENTRIES entries is read block by block each time.
A document whose log perplexity (by byte) is outside its language's band is rejected. The band
reaches LOWER_REACH and UPPER_REACH interquartile ranges beyond the quartiles of the language's
distinct texts, and SHORT over the root of a document's length further, as the mean over few
characters varies more. The upper side is wider, since texts in two languages are good ones.
"""

from __future__ import annotations

import unicodedata
from collections import Counter, OrderedDict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.dataset as ds
from pyarrow import fs
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import as_bytes, batch_of, few, forget, gathered, held, let_go, mark, portions, small_batches, text_or_empty, work_dir, written

ORDER = 5
#: Bytes that are coded at once, n-grams that a task counts before it sends them, entries of a model's block.
PORTION, COUNTED, BLOCK = 500_000, 2_000_000, 1 << 16
#: Entries of models and scored n-grams that a process holds, n-grams that are looked up in a model at once, and bytes of text that are scored together.
ENTRIES, SCORED, ASKED, TOGETHER = 4_000_000, 2_000_000, 60_000, 3_000_000
#: Words for each symbol that a text must have to teach a model.
WORDS_PER_SYMBOL = 10
#: How far bands reach below the first and above the third quartile, in interquartile ranges, and how much further for short texts.
#: Chosen on the labelled texts of scale factor 0.1 with an even id; README.md has the figures on those with an odd one.
LOWER_REACH, UPPER_REACH, SHORT = 5.0, 15.0, 0.5
#: The least interquartile range that a band is made of, where near copies make up most texts of a language.
LEAST_SPREAD = 0.02

# The white space and the symbols of the base rules.
SPACE, MARKS = b" \t\n\x0b\x0c\r", b"#*$%&|<>"

LEAD = b"\0" * (ORDER - 1)


def composed(text: str) -> bytes:
    """UTF-8 with accents in their letters' code points, as far as there are such."""
    return unicodedata.normalize("NFC", text).encode("utf-8", "replace")


def led(data: bytes) -> Iterator[bytes]:
    """The bytes in stretches of PORTION, each behind the ORDER - 1 bytes that it follows; a text follows zeros."""
    data = LEAD + data
    for begin in range(0, max(1, len(data) - len(LEAD)), PORTION):
        yield data[begin : begin + PORTION + len(LEAD)]


def gram_codes(stretches: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(code, which stretch) of the ORDER-gram that ends at each byte."""
    lengths = np.array([len(x) for x in stretches], np.int64) - len(LEAD)
    a = np.frombuffer(b"".join(stretches), np.uint8).astype(np.uint64)
    code = a[ORDER - 1 :].copy()
    for k in range(1, ORDER):
        code |= a[ORDER - 1 - k : len(a) - k] << np.uint64(8 * k)
    which = np.repeat(np.arange(len(stretches)), lengths)
    # bytes of stretch i end after i more leads than those of stretch 0
    return code[np.arange(len(which)) + which * len(LEAD)], which


def text_key(text_col: str = "text") -> list[Column]:
    """A text's 128-bit hash, as (k1, k2)."""
    return [F.xxhash64(text_or_empty(text_col)).alias("k1"), F.xxhash64(F.lit(1), text_or_empty(text_col)).alias("k2")]


def half_of(k1: Column) -> Column:
    """Which half of a language's texts one belongs to, by its hash."""
    return F.pmod(k1, F.lit(2)).cast("int")


def teaches(data: bytes) -> bool:
    """Whether a text takes part in a model."""
    n_words, _, n_symbols, _, n_repeat_words = base_measures(data)
    return n_words >= 50 and 100 * n_repeat_words <= 50 * n_words and n_words >= WORDS_PER_SYMBOL * n_symbols


def count_grams(docs: DataFrame, lang_col: str = "lang", text_col: str = "text") -> DataFrame:
    """(lang, half, code, n) over the distinct texts of each language that teach; a null language is the empty one.

    The rows of a text that occurs n times count 1 / n each, so that texts needn't meet.
    """
    schema = pa.schema([("lang", pa.string()), ("half", pa.int32()), ("code", pa.int64()), ("n", pa.float64())])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        held: dict[tuple[str, int, int], list[np.ndarray]] = {}
        size = 0

        def sent() -> Iterator[pa.RecordBatch]:
            for (lang, half, times), codes in held.items():
                code, n = np.unique(np.concatenate(codes), return_counts=True)
                yield batch_of(schema, {"lang": [lang] * len(code), "half": np.full(len(code), half, np.int32), "code": code.astype(np.int64), "n": n / times})
            held.clear()

        for batch in batches:
            groups: dict[tuple[str, int, int], list[bytes]] = {}
            for lang, half, times, text in zip(*(batch.column(i).to_pylist() for i in range(4))):
                data = text.encode("utf-8", "replace")
                if teaches(data):
                    groups.setdefault((lang, half, times), []).extend(led(composed(text)))
            for key, texts in groups.items():
                for some in portions(texts, PORTION):
                    codes = gram_codes(some)[0]
                    held.setdefault(key, []).append(codes)
                    size += len(codes)
                    if size >= COUNTED:
                        yield from sent()
                        size = 0
        yield from sent()

    keys = docs.select(F.coalesce(lang_col, F.lit("")).alias("lang"), *text_key(text_col), text_or_empty(text_col).alias("text"))
    copies = written(keys.groupBy("lang", "k1", "k2").agg(F.count("*").alias("times")).where("times > 1"), "copies")
    rows = keys.join(few(copies), ["lang", "k1", "k2"], "left").select("lang", half_of(F.col("k1")).alias("half"), F.coalesce("times", F.lit(1)).alias("times"), "text")
    return rows.mapInArrow(count, "lang string, half int, code long, n double").groupBy("lang", "half", "code").agg(F.round(F.sum("n")).cast("long").alias("n"))


def entry_hash(place: int, codes: np.ndarray) -> np.ndarray:
    """Signed 64-bit hashes, one to one, of n-grams and contexts; ``place`` is twice the order, and one more for contexts."""
    x = codes.astype(np.uint64) | np.uint64(place << 56)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ x >> np.uint64(shift)) * np.uint64(factor)
    return (x ^ x >> np.uint64(31)).view(np.int64)


def discounts(orders: list[DataFrame]) -> DataFrame:
    """(order, lang, half, entries, d1, d2, d3): what is taken from counts of 1, 2 and 3 or more; .5, 1, 1.5 where counts of counts are too few."""
    rows = None
    for order, grams in enumerate(orders, 1):
        n = [F.count_if(F.col("n") == k).alias(f"n{k}") for k in range(1, 5)]
        some = grams.groupBy("lang", "half").agg(F.count("*").alias("entries"), *n).select(F.lit(order).alias("order"), "*")
        rows = some if rows is None else rows.unionAll(some)
    few_counts = F.least("n1", "n2", "n3", "n4") == 0
    y = F.try_divide(F.col("n1"), F.col("n1") + 2 * F.col("n2"))
    d = [F.when(few_counts, k / 2).otherwise(F.least(F.greatest(k - (k + 1) * y * F.try_divide(F.col(f"n{k + 1}"), F.col(f"n{k}")), F.lit(0.05)), F.lit(k - 0.05))).alias(f"d{k}") for k in (1, 2, 3)]
    return rows.select("order", "lang", "half", "entries", *d)


def fit_models(grams: DataFrame) -> str:
    """The folder of the models of all languages and halves, a table (lang, half, bucket, n, hashes, x, y) of sorted blocks.

    x and y of an n-gram are its count less its discount and 0, those of a context the total of the
    counts behind it and the share of it that goes to the lower order.
    """
    orders = [written(grams, "grams")]
    for k in range(ORDER - 1, 0, -1):  # lower orders count the different bytes that a gram follows
        shorter = F.col("code").bitwiseAND((1 << 8 * k) - 1).alias("code")
        orders.insert(0, written(orders[0].groupBy("lang", "half", shorter).agg(F.count("*").alias("n")), "grams"))
    taken_of = written(discounts(orders), "discounts")
    most = taken_of.groupBy("lang", "half").agg((2 * F.sum("entries")).alias("e")).agg(F.max("e")).first()[0]
    buckets = max(1, -(-(most or 0) // BLOCK))
    entries = None
    for k, rows in enumerate(orders, 1):
        d = few(taken_of.where(F.col("order") == k).select("lang", "half", "d1", "d2", "d3"))
        rows = rows.join(d, ["lang", "half"]).withColumn("taken", F.when(F.col("n") == 1, F.col("d1")).when(F.col("n") == 2, F.col("d2")).otherwise(F.col("d3")))
        own = rows.select("lang", "half", F.lit(2 * k).alias("place"), "code", (F.col("n") - F.col("taken")).alias("x"), F.lit(0.0).alias("y"))
        contexts = rows.groupBy("lang", "half", F.shiftright("code", 8).alias("code")).agg(F.sum("n").cast("double").alias("x"), (F.sum("taken") / F.sum("n")).alias("y"))
        both = own.unionAll(contexts.select("lang", "half", F.lit(2 * k - 1).alias("place"), "code", "x", "y"))
        entries = both if entries is None else entries.unionAll(both)

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            place, code = b.column("place").to_numpy(), b.column("code").to_numpy()
            h = np.empty(len(code), np.int64)
            for p in np.unique(place):
                h[place == p] = entry_hash(int(p), code[place == p])
            bucket = (h.astype(np.float64) / 2.0**64 + 0.5) * buckets
            yield pa.RecordBatch.from_arrays([b.column("lang"), b.column("half"), pa.array(np.minimum(bucket.astype(np.int64), buckets - 1)), pa.array(h), b.column("x"), b.column("y")], names=["lang", "half", "bucket", "hash", "x", "y"])

    def block(rows: pa.Table) -> pa.Table:
        h = rows.column("hash").to_numpy()
        order = np.argsort(h)
        x, y = (rows.column(c).to_numpy()[order].astype(np.float32).tobytes() for c in "xy")
        one = {c: rows.column(c).slice(0, 1).combine_chunks() for c in ("lang", "half", "bucket")}
        return pa.table(one | {"n": pa.array([len(h)], pa.int64()), "hashes": [h[order].tobytes()], "x": [x], "y": [y]})

    folder = work_dir(grams.sparkSession, "models")
    cells = entries.mapInArrow(hashed, "lang string, half int, bucket long, hash long, x double, y double")
    cells.groupBy("lang", "half", "bucket").applyInArrow(block, "lang string, half int, bucket long, n long, hashes binary, x binary, y binary").write.parquet(folder)
    return folder


class Models:
    """The models in a folder; those that were asked for last are held, as many entries as ENTRIES allows."""

    def __init__(self, folder: str):
        self.store, base = fs.FileSystem.from_uri(folder)
        self.table = ds.dataset(base, filesystem=self.store, format="parquet")
        self.held: OrderedDict[tuple[str, int], list[tuple[np.ndarray, ...]]] = OrderedDict()
        #: Of each model the n-grams that were scored, sorted, and their log probabilities.
        self.scored: OrderedDict[tuple[str, int], tuple[np.ndarray, np.ndarray]] = OrderedDict()

    def blocks(self, lang: str, half: int) -> Iterator[tuple[np.ndarray, ...]]:
        """(hashes, x, y) of each block of a model."""
        if (lang, half) in self.held:
            self.held.move_to_end((lang, half))
            yield from self.held[lang, half]
            return
        keep: list | None = []
        for b in self.table.to_batches(columns=["hashes", "x", "y"], filter=(ds.field("lang") == lang) & (ds.field("half") == half), batch_size=16):
            for h, x, y in zip(*(b.column(i).to_pylist() for i in range(3))):
                one = np.frombuffer(h, np.int64), np.frombuffer(x, np.float32), np.frombuffer(y, np.float32)
                yield one
                if keep is not None:
                    keep.append(one)
                    if sum(len(k[0]) for k in keep[-1:]) + BLOCK * len(keep) > ENTRIES:
                        keep = None
        if keep is not None:
            self.held[lang, half] = keep
            while sum(len(k[0]) for blocks in self.held.values() for k in blocks) > ENTRIES:
                self.held.popitem(last=False)

    def find(self, lang: str, half: int, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """x and y of each of the sorted hashes; zeros where there is none."""
        x, y = np.zeros(len(h)), np.zeros(len(h))
        for hashes, bx, by in self.blocks(lang, half):
            some = slice(*np.searchsorted(h, [hashes[0], hashes[-1]], side="left") + [0, 1])
            at = np.minimum(np.searchsorted(hashes, h[some]), len(hashes) - 1)
            there = hashes[at] == h[some]
            x[some][there], y[some][there] = bx[at[there]], by[at[there]]
        return x, y

    def log_probabilities(self, lang: str, half: int, codes: np.ndarray) -> np.ndarray:
        """Of the last byte of each n-gram after the others, from the lowest order up; 1 in 256 where nothing is known."""
        asked = []
        for k in range(1, ORDER + 1):
            grams = codes & np.uint64((1 << 8 * k) - 1)
            asked += [entry_hash(2 * k, grams), entry_hash(2 * k - 1, grams >> np.uint64(8))]
        h, place = np.unique(np.concatenate(asked), return_inverse=True)
        x, y = (v[place].reshape(ORDER, 2, -1) for v in self.find(lang, half, h))
        p = np.full(len(codes), 1 / 256)
        for own, total, share in zip(x[:, 0], x[:, 1], y[:, 1]):
            p = np.where(total > 0, own / np.maximum(total, 1) + share * p, p)
        return np.log(p)

    def scores(self, lang: str, half: int, codes: np.ndarray) -> np.ndarray:
        """Log probabilities of n-grams, each distinct one looked up once as long as it is held."""
        distinct, place = np.unique(codes, return_inverse=True)
        known, logs = self.scored.pop((lang, half), (np.empty(0, np.uint64), np.empty(0)))
        at = np.searchsorted(known, distinct)
        new = np.ones(len(distinct), bool)
        if len(known):
            new = known[np.minimum(at, len(known) - 1)] != distinct
        if new.any():
            fresh = distinct[new]
            found = np.concatenate([self.log_probabilities(lang, half, fresh[i : i + ASKED]) for i in range(0, len(fresh), ASKED)])
            if len(known) + len(fresh) > SCORED // 2:
                known, logs, at = known[:0], logs[:0], at * 0
                fresh, found = distinct, (found if new.all() else np.concatenate([self.log_probabilities(lang, half, distinct[i : i + ASKED]) for i in range(0, len(distinct), ASKED)]))
            merged = np.concatenate([known, fresh])
            order = np.argsort(merged, kind="stable")
            known, logs = merged[order], np.concatenate([logs, found])[order]
            at = np.searchsorted(known, distinct)
        self.scored[lang, half] = known, logs
        while sum(len(k) for k, _ in self.scored.values()) > SCORED and len(self.scored) > 1:
            self.scored.popitem(last=False)
        return logs[at][place]


def base_measures(data: bytes) -> tuple[int, int, int, int, int]:
    """(n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words) of a text's UTF-8 bytes."""
    words = data.split()
    bare = data.translate(None, SPACE)
    lines = [x for x in data.split(b"\n") if x.translate(None, SPACE)]
    windows = list(zip(words, words[1:], words[2:]))
    repeated = 0
    if len(set(windows)) < len(windows):
        often, end = {w for w, n in Counter(windows).items() if n > 1}, 0
        for i, w in enumerate(windows):
            if w in often:
                repeated += i + 3 - max(end, i)
                end = i + 3
    return len(words), len(bare.decode("utf-8", "replace")), len(data) - len(data.translate(None, MARKS)), len(lines) - len(set(lines)), repeated


MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def score(docs: DataFrame, keep: list[str], lang_col: str = "lang", text_col: str = "text") -> DataFrame:
    """(row, lang, k1, k2, measures, log_perplexity) of each document, ``row`` being a struct of the columns ``keep`` and k1, k2 the text's hash.

    Reads the documents three times, to find copies, to count and to score. Models stay in the shared folder, where tasks read them.
    """
    small_batches(docs.sparkSession)
    folder = fit_models(count_grams(docs, lang_col, text_col))
    rows = docs.select(F.coalesce(lang_col, F.lit("")).alias("lang"), text_or_empty(text_col).alias("text"), *text_key(text_col), F.struct(*[F.col(f"`{c}`") for c in keep]).alias("row"))
    rows = rows.withColumn("other", 1 - half_of(F.col("k1")))
    fields = [("lang", pa.string()), ("k1", pa.int64()), ("k2", pa.int64()), *((m, pa.int64()) for m in MEASURES), ("log_perplexity", pa.float64())]

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        models = held(("models", folder), lambda: Models(folder))
        for batch in gathered(batches, "text", TOGETHER):
            langs, texts = batch.column("lang").to_pylist(), batch.column("text").to_pylist()
            loss, length = np.zeros(len(texts)), np.ones(len(texts))
            groups: dict[tuple[str, int], tuple[list[bytes], list[int]]] = {}
            for i, key in enumerate(zip(langs, batch.column("other").to_pylist())):
                stretches, of = groups.setdefault(key, ([], []))
                for x in led(composed(texts[i])):
                    stretches.append(x)
                    of.append(i)
            for (lang, half), (stretches, of) in groups.items():
                begin = 0
                for some in portions(stretches, PORTION):
                    codes, which = gram_codes(some)
                    sums = np.bincount(which, weights=models.scores(lang, half, codes), minlength=len(some))
                    np.add.at(loss, of[begin : begin + len(some)], -sums)
                    np.add.at(length, of[begin : begin + len(some)], [len(x) - len(LEAD) for x in some])
                    begin += len(some)
            loss /= np.maximum(1, length - 1)
            found = list(zip(*map(base_measures, as_bytes(batch.column("text"))))) or [[]] * len(MEASURES)
            columns = [batch.column("row"), pa.array(langs, pa.string()), batch.column("k1"), batch.column("k2"), *(pa.array(x, pa.int64()) for x in found), pa.array(loss)]
            yield pa.RecordBatch.from_arrays(columns, names=["row", *(n for n, _ in fields)])

    schema = T.StructType([T.StructField("row", rows.schema["row"].dataType), T.StructField("lang", T.StringType()), T.StructField("k1", T.LongType()), T.StructField("k2", T.LongType()), *(T.StructField(m, T.LongType()) for m in MEASURES), T.StructField("log_perplexity", T.DoubleType())])
    return rows.mapInArrow(measure, schema)


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def judge(docs: DataFrame, keep: list[str] | None = None, lang_col: str = "lang", text_col: str = "text") -> DataFrame:
    """(row, lang, measures, log_perplexity, lower, upper, base_failed, kept) of each document.

    ``row`` is a struct of the columns ``keep`` (all of ``docs`` unless given). Bands come from the
    distinct texts of each language that pass the base rules, with a spread of LEAST_SPREAD at least. A null text is an empty one and a null
    language the empty one, with a band of its own; empty texts fail the base rules, repeated rows
    are judged alike, and an empty table stays empty.
    """
    since = mark()
    scored = written(score(docs, docs.columns if keep is None else keep, lang_col, text_col), "scored").withColumn("base_failed", base_failed())
    forget(docs.sparkSession, since)
    texts = scored.where(~F.col("base_failed")).groupBy("lang", "k1", "k2").agg(F.min("log_perplexity").alias("log_perplexity"))
    quartiles = texts.groupBy("lang").agg(F.percentile_approx("log_perplexity", [0.25, 0.75], 10_000).alias("q"))
    spread = F.greatest(F.col("q")[1] - F.col("q")[0], F.lit(LEAST_SPREAD))
    bands = quartiles.select("lang", (F.col("q")[0] - F.lit(LOWER_REACH) * spread).alias("lower"), (F.col("q")[1] + F.lit(UPPER_REACH) * spread).alias("upper"))
    varies = F.lit(SHORT) / F.sqrt(F.greatest(F.lit(1), "word_chars"))
    inside = F.col("log_perplexity").between(F.col("lower") - varies, F.col("upper") + varies)
    small = bands.count() <= 100_000  # a row for each language
    return scored.drop("k1", "k2").join(F.broadcast(bands) if small else bands, "lang", "left").withColumn("kept", ~F.col("base_failed") & F.coalesce(inside, F.lit(True)))


def keep_good(docs: DataFrame, lang_col: str = "lang", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that ``judge`` keeps, unchanged.

    A verdict follows from text and language, so what is written and joined are the rejected texts'
    128-bit hashes and languages, not the texts.
    """
    key = {"_k1": F.xxhash64(text_or_empty(text_col)), "_k2": F.xxhash64(F.lit(1), text_or_empty(text_col)), "_lang": F.coalesce(lang_col, F.lit(""))}
    columns = docs.columns
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in columns]).alias("_row"), F.col(lang_col).alias("lang"), F.col(text_col).alias("text"), *[v.alias(k) for k, v in key.items()])
    since = mark()
    rejected = written(judge(keyed, keep=["_k1", "_k2"]).where(~F.col("kept")).select("row.*", F.col("lang").alias("_lang")).distinct(), "rejected")
    forget(docs.sparkSession, since)
    return keyed.join(few(rejected), ["_k1", "_k2", "_lang"], "left_anti").select("_row.*")
