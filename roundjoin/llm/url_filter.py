"""URL filters: rules by host and path first; else unigram Viterbi splits the names in a host into words, and multinomial naive Bayes scores the words
of host and path."""

from __future__ import annotations

import math
from collections import Counter
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, pick, spread_join

#: Rules (host, path) of each verdict.
RULES = {"net/": "block", "example.net/en/": "allow", "example.com/de/": "block", "org/fr/": "allow"}
#: Labelled names that the classifier learns from, as lists of words.
BLOCKED_NAMES = (
    "cheap pills pharmacy", "discount viagra pills", "buy pills online cheap", "casino bonus win", "online casino jackpot", "win lottery prize", "free bets odds", "sports bets bonus",
    "poker slots roulette", "spam link farm", "content farm spam", "ads track click", "ad server banner", "track user ads", "popup ads click", "adult cams xxx", "porn videos free xxx", "sex chat cams",
    "payday loans fast", "easy credit loans", "replica watches cheap", "fake luxury replica", "weight loss miracle pills", "crack keygen warez", "torrent warez crack", "hot singles dating", "bitcoin double scam",
    "phishing login scam", "malware download free", "bet win casino",
)
ALLOWED_NAMES = (
    "city news daily", "university library archive", "public school board", "science journal articles", "history museum guide", "weather forecast report", "open source software docs", "health ministry advice",
    "garden recipes kitchen", "travel guide maps", "local government office", "world health report", "music festival program", "book reviews club", "research institute papers", "math lecture notes", "language course lessons",
    "photo gallery art", "football club news", "theatre and film", "child care parents", "nature park birds", "law courts archive", "engineering blog posts", "the daily times", "community forum help", "bank and insurance",
    "market prices today", "job training center", "family doctor advice",
)
_WORD = r"[\p{L}\p{M}]+"
#: Production value: what each letter of an unknown stretch costs.
UNKNOWN_LETTER = 2.5
_PLAIN = frozenset(("www", "m", "com", "org", "net", "example", "html", "http", "https"))


@dataclass
class Segmenter:
    """Unigram model: splits a name into the words of highest total log probability. An unknown stretch, of any length, costs more the longer it is."""

    costs: dict[str, float]
    unknown: float

    def __post_init__(self):
        self.lengths = sorted({len(w) for w in self.costs})

    @classmethod
    def of(cls, counts: dict[str, int], total: int | None = None) -> Segmenter:
        """counts may hold only the words that are in the names to split if total is that of all."""
        total = (sum(counts.values()) if total is None else total) + 1
        return cls({w: math.log(total / n) for w, n in counts.items()}, math.log(total))

    def split(self, name: str) -> list[str]:
        """Viterbi: for each end the best split up to it, and the best whose last stretch is unknown and may grow. Ties go to the longer last word."""
        best: list[tuple[float, int]] = [(0.0, 0)]
        stretch: tuple[float, int] = (math.inf, 0)
        for end in range(1, len(name) + 1):
            fresh = (best[end - 1][0] + self.unknown + UNKNOWN_LETTER, end - 1)
            stretch = min((stretch[0] + UNKNOWN_LETTER, stretch[1]), fresh)
            known = [(best[end - n][0] + self.costs[name[end - n : end]], end - n) for n in self.lengths if n <= end and name[end - n : end] in self.costs]
            best.append(min((stretch, *known)))
        out, end = [], len(name)
        while end:
            out.append(name[best[end][1] : end])
            end = best[end][1]
        return out[::-1]


@dataclass
class NaiveBayes:
    """Multinomial model with add-one smoothing and equal priors; words that it never saw say nothing."""

    weights: dict[str, float]

    @classmethod
    def of(cls, blocked: list[list[str]], allowed: list[list[str]]) -> NaiveBayes:
        return cls.counted(Counter(w for x in blocked for w in x), Counter(w for x in allowed for w in x))

    @classmethod
    def counted(cls, bad: dict[str, int], good: dict[str, int]) -> NaiveBayes:
        bad, good = Counter(bad), Counter(good)
        words = bad.keys() | good.keys()
        nb, ng = sum(bad.values()) + len(words), sum(good.values()) + len(words)
        return cls({w: math.log((bad[w] + 1) / nb) - math.log((good[w] + 1) / ng) for w in words})

    def score(self, words: list[str]) -> float:
        return sum(self.weights.get(w, 0.0) for w in words)


def corpus_words(pages: DataFrame) -> DataFrame:
    """w, n: how often each word stands in all page texts."""
    words = pick(pages, "html").select(F.explode(F.regexp_extract_all(F.regexp_replace(F.lower(F.col("html").cast("string")), "<[^>]*>", " "), F.lit(_WORD), F.lit(0))).alias("w"))
    return words.groupBy("w").agg(F.count("*").alias("n"))


def split_names(names: DataFrame, counts: DataFrame, known: Counter, total: int) -> DataFrame:
    """name, split (its words), n (rows) for each distinct name. counts: w, n, all words of the corpus; known: counts that are added to them; total: of all.

    A name meets the counted words in it by a join on its substrings of those lengths that counted words have (few, though the longest may be long), so tasks
    hold the words of single names only. The driver gets the lengths."""
    lengths = sorted(r.m for r in counts.select(F.length("w").alias("m")).distinct().collect())
    names = cut(names.groupBy("name").agg(F.count("*").alias("n")).select("name", "n", F.monotonically_increasing_id().alias("id")))

    def substrings(batches):
        for b in batches:
            for i, name in zip(b.column("id").to_pylist(), b.column("name").to_pylist(), strict=True):
                subs = list({name[at : at + n] for n in lengths if n <= len(name) for at in range(len(name) - n + 1)})
                for k in range(0, len(subs), 10_000):
                    part = subs[k : k + 10_000]
                    yield pa.record_batch([pa.array([i] * len(part), pa.int64()), pa.array(part, pa.string())], names=["id", "w"])

    def run(batches):
        for b in batches:
            out = []
            for name, found in zip(b.column("name").to_pylist(), b.column("found").to_pylist(), strict=True):
                own = Counter({x["w"]: x["n"] for x in found or ()})
                own.update({w: n for w, n in known.items() if w in name})
                out.append(Segmenter.of(own, total).split(name))
            yield pa.record_batch([b.column("name"), b.column("n"), pa.array(out, pa.list_(pa.string()))], names=["name", "n", "split"])

    within = cut(names.select("id", "name").mapInArrow(substrings, "id long, w string"))
    met = within.groupBy("w").agg(F.count("*").alias("rows")).join(counts, "w")
    found = spread_join(within, cut(met), "w", "id", count="rows").groupBy("id").agg(F.collect_list(F.struct("w", "n")).alias("found"))
    return names.join(found, "id", "left").select("name", "n", "found").mapInArrow(run, "name string, n long, split array<string>")


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host (A-Z as a-z) and path; both empty for a null or a text without ://."""
    has = F.coalesce(url.contains("://"), F.lit(False))
    rest = F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1)
    host = F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.when(has, host).otherwise(""), F.when(has, path).otherwise("")


def match_rule(host: Column, path: Column, rules: dict[str, str]) -> Column:
    """The longest rule (ties by code point) whose host is the url's or a parent of it and whose path begins the url's; null if none."""
    out = F.lit(None).cast("string")
    for rule in sorted(rules, key=lambda r: (len(r), r)):
        name, slash, tail = rule.partition("/")
        fits = ((host == name) | host.endswith(f".{name}")) & path.startswith(slash + tail)
        out = F.when(fits, F.lit(rule)).otherwise(out)
    return out


def seed_names() -> list[tuple[str, bool]]:
    """The labelled names that stand above: text, and whether it is blocked."""
    return [(x, True) for x in BLOCKED_NAMES] + [(x, False) for x in ALLOWED_NAMES]


def train_words(labelled: DataFrame) -> tuple[NaiveBayes, Counter]:
    """The classifier, and how often each of its words was seen. labelled: name (words, or a host or url whose letters are words), blocked.

    Words are counted where the table lies; the driver gets the counts, one row for each word of the labelled names. Rows with nulls are no examples."""
    words = pick(labelled, "name", "blocked").where("name IS NOT NULL AND blocked IS NOT NULL").select("blocked", F.explode(F.regexp_extract_all(F.lower("name"), F.lit(_WORD), F.lit(0))).alias("w"))
    seen = words.where(~F.col("w").isin(*_PLAIN)).groupBy("w").agg(F.count_if("blocked").alias("bad"), F.count_if(~F.col("blocked")).alias("good")).collect()
    return NaiveBayes.counted({r.w: r.bad for r in seen}, {r.w: r.good for r in seen}), Counter({r.w: r.bad + r.good for r in seen})


def judge_urls(pages: DataFrame, rules: dict[str, str] | None = None, labelled: DataFrame | None = None) -> DataFrame:
    """page_id, host, path, rule, verdict, words (of host and path), score (over 0: like the blocked names) for every row of pages.

    labelled: names that the classifier learns from (name, blocked); without it, seed_names(). Names are split at what is no letter, in any script; %-encoded
    letters of paths count as themselves. Null urls and those without :// have an empty host and path, no words, score 0 and verdict allow; score 0 is allow;
    nulls in html add no words; repeated rows are judged each; a null page_id stays; an empty table gives no rows; other columns are ignored. One row of totals,
    the lengths of words and the words of the labelled names come to the driver."""
    spark = pages.sparkSession
    rules = RULES if rules is None else rules
    counts = cut(corpus_words(pages))
    sums = counts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("total"), F.coalesce(F.max("n"), F.lit(1)).alias("most")).first()
    weight = max(1, sums.most // 1000)
    bayes, seen = train_words(spark.createDataFrame(seed_names(), "name string, blocked boolean") if labelled is None else labelled)
    known = Counter({w: n * weight for w, n in seen.items()})
    host, path = url_parts(F.col("url"))
    rows = pick(pages, "page_id", "url").select("page_id", host.alias("host"), path.alias("path"))
    rows = cut(rows.withColumn("rule", match_rule(F.col("host"), F.col("path"), rules)).withColumn("id", F.monotonically_increasing_id()))
    shown = F.lower(F.coalesce(F.try_url_decode("path"), F.col("path")))
    parts = F.filter(F.concat(F.regexp_extract_all("host", F.lit(_WORD), F.lit(0)), F.regexp_extract_all(shown, F.lit(_WORD), F.lit(0))), lambda x: ~x.isin(*_PLAIN))
    names = rows.select("id", F.posexplode(parts).alias("at", "name"))
    parted = spread_join(names, cut(split_names(names.select("name"), counts, known, sums.total + sum(known.values()))), "name", "id")
    ordered = F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("at", "split"))), lambda x: x["split"]))
    words = parted.groupBy("id").agg(F.array_join(ordered, " ").alias("words"))
    rows = rows.join(words, "id", "left").select("page_id", "host", "path", "rule", F.coalesce("words", F.lit("")).alias("words"))

    def run(batches):
        for b in batches:
            scores = [bayes.score(x.split()) for x in b.column("words").to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(scores, pa.float64())], names=[*b.schema.names, "score"])

    scored = rows.mapInArrow(run, T.StructType([*rows.schema, T.StructField("score", T.DoubleType())]))
    by_rule = F.lit(None).cast("string")
    for rule, verdict in rules.items():
        by_rule = F.when(F.col("rule") == rule, verdict).otherwise(by_rule)
    return scored.select("page_id", "host", "path", "rule", F.coalesce(by_rule, F.when(F.col("score") > 0, "block").otherwise("allow")).alias("verdict"), "words", "score")
