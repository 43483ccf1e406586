"""Toxicity: a weighted lexicon matched by Aho-Corasick on folded text.

Folding lower-cases, maps look-alike letters of other alphabets and digit or sign
substitutions to Latin letters, and drops zero-width and combining marks; runs of
other characters become one blank, so every lexicon entry is anchored at a word start.

Training takes about ``TRAIN_ROWS`` labelled rows at most, those whose id hashes below a
threshold set by the number of labels; so bounded, their ids are broadcast and the texts
picked in the scan. Spark counts, for both labels, the documents that hold
each word-start prefix of 3 to 8 characters. An entry is a prefix with enough toxic
documents whose log-odds exceed a bound. It gives way to an extension that holds nearly
all its documents, and to a shorter remaining entry; its weight is the log-odds. Exception phrases are whole words (learned: they
extend an entry, yet clean documents hold them at least as often) and the given
phrases; a match inside one counts nothing.

What training reads and keeps is bounded by parameters: ``TRAIN_ROWS`` and ``FIT_ROWS`` labelled rows; of the
candidates, the ``MAX_ENTRIES`` prefixes in most toxic documents and the ``MAX_ENTRIES`` exceptions in most clean
ones; a word of over ``MAX_WORD`` characters is no exception. Scoring reads every whole text.

Score: weights of all matches over (words + prior words), mapped to 0..1 so that the
cut between the two labels' scores, fitted on a bounded sample of the training rows, is 0.5.

Defined results: null and blank texts score as no match; with no labelled rows, or
none of one label, the lexicon is empty and every score is below 0.5; repeated rows
score alike, and rows that repeat a labelled id all train; a row without an id is scored and trains
nothing; entries of equal counts go by length, then text; a very long text is one row of one task; an empty table gives
an empty result; extra columns are ignored, and the stage passes them on whatever their names.
"""

from __future__ import annotations

import math
import unicodedata
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulecredit.llm.runtime import SharedStore, ship

PREFIX_LENGTHS = range(3, 9)
#: An entry needs this share of the toxic documents (and at least 5 of them), and these log-odds.
MIN_SHARE, MIN_DOCS, MIN_LOG_ODDS = 0.01, 5, 3.0
MAX_ENTRIES, MAX_WORD = 2_000, 40
#: Labelled rows the lexicon is learned from, at most (up to the spread of a hash threshold).
TRAIN_ROWS = 40_000
#: Labelled rows used to fit the cut, about (by a hash threshold).
FIT_ROWS = 20_000
PRIOR_WORDS = 20.0
#: Harmless phrases that hold entries of an English insult list.
EXCEPTION_PHRASES = ("trash can", "trash bin", "trash bag", "clown fish", "clownfish", "class clown")

#: Look-alikes (Cyrillic, Greek, full-width forms are folded by rule) and substitutions.
LOOKALIKES = {
    "а": "a", "в": "b", "с": "c", "ԁ": "d", "е": "e", "ё": "e", "һ": "h", "н": "h", "і": "i", "ї": "i", "ј": "j", "к": "k",
    "ӏ": "l", "м": "m", "о": "o", "р": "p", "ԛ": "q", "г": "r", "ѕ": "s", "т": "t", "ц": "u", "ѵ": "v", "ԝ": "w", "х": "x", "у": "y",
    "α": "a", "β": "b", "ϲ": "c", "ε": "e", "η": "n", "ι": "i", "κ": "k", "ν": "v", "ο": "o", "ρ": "p", "σ": "o", "τ": "t", "υ": "u",
    "χ": "x", "ω": "w", "γ": "y", "ı": "i", "ɑ": "a", "ɡ": "g", "ɩ": "i", "ʟ": "l", "ꜱ": "s", "ᴏ": "o",
}
SUBSTITUTES = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "@": "a", "$": "s", "!": "i"}


class _Fold(dict):
    """str.translate table, filled on demand and bounded by the number of code points."""

    def __missing__(self, code: int) -> str:
        c = chr(code)
        out = LOOKALIKES.get(c) or SUBSTITUTES.get(c)
        if out is None:
            out = ""
            for x in unicodedata.normalize("NFKC", c).lower():
                x = LOOKALIKES.get(x) or SUBSTITUTES.get(x) or x
                kind = unicodedata.category(x)
                out += "" if kind in ("Mn", "Me", "Cf") else x if kind[0] in "LN" or len(x) > 1 else " "
        self[code] = out
        return out


_fold = _Fold()


def fold(text: str) -> str:
    """Folded text: words in single blanks, one at either end."""
    return f" {' '.join(unicodedata.normalize('NFC', text).translate(_fold).split())} "


def _word_docs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(feature, toxic): the distinct words and word-start prefixes of each text, in small batches."""

    def flush() -> pa.RecordBatch:
        made = [pa.array(out, pa.string()), pa.array(label, pa.int32())]
        out.clear()
        label.clear()
        return pa.RecordBatch.from_arrays(made, ["feature", "toxic"])

    out: list[str] = []
    label: list[int] = []
    for b in batches:
        for text, toxic in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            found: set[str] = set()
            for w in set(fold(text or "").split()):
                found.update(w[:n] for n in PREFIX_LENGTHS if len(w) >= n)
                if len(w) <= MAX_WORD:
                    found.add(w + " ")
            out.extend(found)
            label.extend([toxic] * len(found))
            if len(out) > 100_000:
                yield flush()
    yield flush()


@dataclass(frozen=True)
class Lexicon:
    weights: dict[str, float]
    exceptions: tuple[str, ...]
    cut: float = 0.0


def learn_lexicon(labelled: DataFrame) -> Lexicon:
    """Entries and exceptions from (text, toxic); reads every row given."""
    ship(labelled.sparkSession)
    rows = labelled.where("toxic is not null").select("text", F.col("toxic").cast("int").alias("toxic"))
    totals = {r["toxic"]: r["n"] for r in rows.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    bad, good = totals.get(1, 0), totals.get(0, 0)
    if not bad or not good:
        return Lexicon({}, EXCEPTION_PHRASES)
    least = max(MIN_DOCS, math.ceil(MIN_SHARE * bad))
    counts = rows.mapInArrow(_word_docs, "feature string, toxic int").groupBy("feature").agg(
        F.count_if(F.col("toxic") == 1).alias("b"), F.count_if(F.col("toxic") == 0).alias("g")
    )
    odds = F.log((F.col("b") + 0.5) / (bad + 1.0)) - F.log((F.col("g") + 0.5) / (good + 1.0))
    top = (
        counts.where(~F.col("feature").endswith(" ") & (F.col("b") >= least))
        .withColumn("w", F.round(odds, 6))
        .where(F.col("w") >= MIN_LOG_ODDS)
        .orderBy(F.desc("b"), F.length("feature"), "feature")
        .limit(MAX_ENTRIES)
        .select("feature", "b", "g", "w")
        .collect()
    )
    # a prefix whose extension holds nearly all of its documents gives way to the extension
    longer: dict[str, int] = {}
    for r in top:
        stem = r["feature"][:-1]
        longer[stem] = max(longer.get(stem, 0), r["b"])
    top = [r for r in top if longer.get(r["feature"], 0) < 0.9 * r["b"]]
    entries: dict[str, float] = {}
    for r in sorted(top, key=lambda r: (len(r["feature"]), r["feature"])):
        if not any(r["feature"][:n] in entries for n in range(1, len(r["feature"]))):
            entries[r["feature"]] = r["w"]
    if not entries:
        return Lexicon({}, EXCEPTION_PHRASES)
    starts = F.lit(False)
    for n in PREFIX_LENGTHS:
        own = [e for e in entries if len(e) == n]
        if own:
            starts = starts | F.substring("feature", 1, n).isin(own)
    words = (
        counts.where(F.col("feature").endswith(" ") & starts & (F.col("g") > 0) & (F.col("g") * bad >= F.col("b") * good))
        .orderBy(F.desc("g"), "feature")
        .limit(MAX_ENTRIES)
        .select("feature")
        .collect()
    )
    learned = tuple(r["feature"].strip() for r in words)
    return Lexicon(entries, EXCEPTION_PHRASES + learned)


class Matcher:
    def __init__(self, lexicon: Lexicon):
        import ahocorasick

        self.lexicon = lexicon
        self.machine = ahocorasick.Automaton()
        for e, w in lexicon.weights.items():
            self.machine.add_word(" " + e, (len(e) + 1, w))
        for p in lexicon.exceptions:
            # spanning blanks on both sides: whole words only
            key = f" {p} "
            if key not in self.machine:
                self.machine.add_word(key, (len(key), None))
        if len(self.machine):
            self.machine.make_automaton()

    def weight(self, text: str) -> float:
        """Summed weights of the matches outside exception phrases, over the length."""
        folded = fold(text)
        hits: list[tuple[int, float]] = []
        safe: list[tuple[int, int]] = []
        if len(self.machine):
            for end, (size, w) in self.machine.iter(folded):
                if w is None:
                    safe.append((end - size + 1, end))
                else:
                    hits.append((end - size + 1, w))
        if safe:
            hits = [(s, w) for s, w in hits if not any(a <= s < b for a, b in safe)]
        return sum(w for _, w in hits) / (folded.count(" ") - 1 + PRIOR_WORDS)

    def score(self, text: str) -> float:
        """0 to 1; 0.5 at the fitted cut."""
        x, cut = self.weight(text), self.lexicon.cut
        return round(x / (x + cut), 9) if x > 0 and cut > 0 else 0.0


def fit_cut(weights: list[tuple[float, int]]) -> float:
    """The positive cut with the fewest errors, in the middle of its gap."""
    points = sorted(weights)
    values = sorted({w for w, _ in points if w > 0})
    if not values:
        return 1.0
    bad_above = sum(1 for w, y in points if w > 0 and y == 1)
    good_above = sum(1 for w, y in points if w > 0 and y == 0)
    bad_below = sum(1 for w, y in points if w <= 0 and y == 1)
    best, at, i = bad_below + good_above, values[0] / 2, 0
    rows = [p for p in points if p[0] > 0]
    for k, v in enumerate(values[:-1]):
        while i < len(rows) and rows[i][0] <= v:
            bad_below += rows[i][1] == 1
            good_above -= rows[i][1] == 0
            bad_above -= rows[i][1] == 1
            i += 1
        if bad_below + good_above < best:
            best, at = bad_below + good_above, (v + values[k + 1]) / 2
    return at


def _weights(lexicon: Lexicon, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    m = Matcher(lexicon)
    for b in batches:
        out = [m.weight(t or "") for t in b.column(0).to_pylist()]
        yield pa.RecordBatch.from_arrays([pa.array(out, pa.float64()), b.column(1)], ["weight", "toxic"])


def train(labelled: DataFrame) -> Lexicon:
    """A fitted lexicon from (doc_id, text, toxic)."""
    lexicon = learn_lexicon(labelled)
    if not lexicon.weights:
        return lexicon
    share = FIT_ROWS / max(labelled.count(), FIT_ROWS)
    picked = labelled.where(F.pmod(F.xxhash64("doc_id", F.lit("fit")), F.lit(1 << 30)) < int(share * (1 << 30)))
    sample = picked.where("toxic is not null").select("text", F.col("toxic").cast("int").alias("toxic"))
    got = sample.mapInArrow(lambda it: _weights(lexicon, it), "weight double, toxic int").collect()
    return Lexicon(lexicon.weights, lexicon.exceptions, fit_cut([(r["weight"], r["toxic"]) for r in got]))


def score_documents(docs: DataFrame, lexicon: Lexicon) -> DataFrame:
    """(doc_id, score) of every row; only ``text`` enters a score."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = Matcher(lexicon)
        for b in batches:
            out = [m.score(t or "") for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.float64())], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double")


def held_out(doc_id=None):
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0


def training_rows(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, text, toxic) of about TRAIN_ROWS labelled documents at most outside the held-out fifth, written once."""
    rows = labels.where(~held_out()).where("toxic is not null").select(F.col("doc_id").cast("long").alias("doc_id"), "toxic")
    total = rows.count()
    if total > TRAIN_ROWS:  # by a hash threshold: no task has to merge the samples of all others
        bound = int(TRAIN_ROWS / total * (1 << 30))
        rows = rows.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < bound)
    chosen = rows
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return SharedStore(docs.sparkSession, "toxicity").write(texts.join(F.broadcast(chosen), "doc_id"), "training")


def op8_toxicity_lexicon(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    scored = score_documents(docs, train(training_rows(docs, labels)))
    return scored.select("doc_id", held_out().alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"))


def clean_documents(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The documents scored below 0.5, with exactly the input's columns.

    The lexicon is trained on the labelled rows of ``docs``. Rows are judged where
    they stand: the score is one more column of the same pass over the texts.
    """
    lexicon = train(training_rows(docs, labels))
    cols = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = Matcher(lexicon)
        for b in batches:
            keep = [m.score(t or "") < 0.5 for t in b.column(cols.index("text")).to_pylist()]
            yield b.filter(pa.array(keep, pa.bool_()))

    ship(docs.sparkSession)
    return docs.mapInArrow(run, docs.schema)
