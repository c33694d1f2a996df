"""Operator 4, URL filters: longest-suffix rules, then words in the host scored by naive Bayes.

Host, path and the rule that fits are plain SQL expressions. Where no rule fits, host labels and
path parts are split into words by a unigram Viterbi search (so that run-together names come
apart), and a multinomial naive Bayes model scores the words. Words are counted over all pages' texts (the
dictionary keeps the ``VOCABULARY`` most frequent, which bounds the model, not the count); the weights come from
the labelled names below; a caller can pass others. The rules' own verdicts are no labels, as they tell languages apart.

Null urls and urls without ``://`` have empty host and path, no rule, and the verdict of no words
(allow). Ties between rules of one length go to the smaller rule. Texts and urls of any length are read whole: a run of
letters costs time in proportion to its length. Null html counts no words. Repeated rows are judged
alike; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .store import materialize, remove

RULES = (("allow", "com", "/"), ("block", "example.com", "/en/"), ("allow", "www.example.com", "/en/"), ("block", "net", "/es/"), ("block", "net", "/fr/"))

# Labelled training names, one name per entry, words joined by hyphens.
BLOCKED_NAMES = """casino-win online-casino-bonus free-slots poker-bet bet-live sports-betting-odds jackpot-spin cheap-pills buy-pills-online
pharmacy-discount-meds viagra-cialis-cheap weight-loss-miracle porn-tube adult-sex-cams xxx-video nude-girls hot-escort-dating sex-chat-live
payday-loans-fast easy-cash-loan get-rich-quick crypto-double-profit forex-signals-win replica-watches cheap-replica-bags crack-keygen
popup-ad-network banner-ads-server click-tracker warez-download torrent-free-movies serial-crack hack-password free-iphone-win-prize lottery-winner click-here-free spam-mail-bulk
fake-id-buy essay-writing-cheap seo-backlinks-buy followers-likes-cheap gamble-roulette-blackjack steroid-shop"""
ALLOWED_NAMES = """daily-news city-news-today weather-report science-journal history-museum public-library school-education university-research
open-source-software code-docs travel-guide food-recipes garden-home health-care hospital-info music-review film-review book-club sports-news
football-results art-gallery photo-blog family-blog personal-blog tech-blog world-map government-services local-council bank-help user-forum
support-help product-manual company-about contact-us learning-center language-course data-archive mobile-site news-feed english-lessons
articles-page index-home post-comment page-list search-results stock-market climate-report law-review"""
STRIP = frozenset("www com org net example html htm php http https index m mobile blog static cdn img api web en de fr es".split())
_CHUNK = re.compile(r"[^\W\d_]+")
#: Words of the corpus in the dictionary, and their longest; the smoothing of the weights.
VOCABULARY, LONGEST, SMOOTH = 50_000, 24, 0.1


def corpus_words(pages: DataFrame, vocabulary: int = VOCABULARY) -> dict[str, int]:
    """The most frequent words of all pages' texts with their counts, ``vocabulary`` of them at most.

    A histogram of the counts (a few hundred rows) gives the least count that is kept, so the driver gets the dictionary
    and no more, however many partitions there are; of words near that count all stay or all go.
    """
    text = F.regexp_replace(F.lower("html"), r"(?s)<(?:script|style)\b.*?</(?:script|style)>|<[^>]*>|&[#\w]*;", " ")
    words = pages.select(F.explode(F.split(text, r"[^\p{L}]+")).alias("word")).filter(F.length("word").between(2, LONGEST))
    counts = materialize(words.groupBy("word").agg(F.count("*").alias("n")).withColumn("size", F.floor(F.log2("n") * 16).cast("int")), "words")
    total, least = 0, 0
    for row in counts.groupBy("size").agg(F.count("*").alias("words")).orderBy(F.desc("size")).collect():
        total += row["words"]
        if total > vocabulary:
            least = row["size"] + 1
            break
    found = {r["word"]: r["n"] for r in counts.filter(F.col("size") >= least).select("word", "n").collect()}
    remove(counts)
    return found


class NameModel:
    """Unigram dictionary of corpus counts and labelled names; naive Bayes weights from two lists of names."""

    def __init__(self, blocked: str = BLOCKED_NAMES, allowed: str = ALLOWED_NAMES, prior: float = 0.2, counts: dict[str, int] | None = None, smooth: float = SMOOTH):
        lists = [Counter(re.split(r"[\s-]+", x.strip())) for x in (allowed, blocked)]
        named = set(lists[0]) | set(lists[1])
        known = Counter(counts or {})
        for w in named:
            known[w] += lists[0][w] + lists[1][w]
        total = sum(known.values())
        self.cost = {w: -math.log(n / total) for w, n in known.items()}
        self.longest = max(map(len, known))
        self.total = total
        sums = [sum(c.values()) + smooth * len(named) for c in lists]
        self.weight = {w: math.log((lists[1][w] + smooth) / sums[1]) - math.log((lists[0][w] + smooth) / sums[0]) for w in named}
        self.bias = math.log(prior / (1 - prior))
        self.memo: dict[str, tuple[str, ...]] = {}

    def segment(self, chunk: str) -> tuple[str, ...]:
        """The split of least cost; an unknown run costs more with each letter."""
        if chunk in self.memo:
            return self.memo[chunk]
        n = len(chunk)
        start = math.log(10 * self.total)  # an unknown run pays this once, and 2 for each letter
        # best[i][u]: least cost of the first i letters, u = 1 where they end in an unknown letter
        best = [[math.inf, math.inf] for _ in range(n + 1)]
        back: list[list[tuple[int, int]]] = [[(0, 0), (0, 0)] for _ in range(n + 1)]
        best[0][0] = 0.0
        for i in range(1, n + 1):
            for j in range(max(0, i - self.longest), i):
                c = self.cost.get(chunk[j:i])
                if c is not None:
                    for u in (0, 1):
                        if best[j][u] + c < best[i][0]:
                            best[i][0], back[i][0] = best[j][u] + c, (j, u)
            for u in (0, 1):
                c = best[i - 1][u] + 2.0 + (0 if u else start)
                if c < best[i][1]:
                    best[i][1], back[i][1] = c, (i - 1, u)
        out: list[str] = []
        run, i, u = "", n, int(best[n][1] < best[n][0])
        while i > 0:
            j, before = back[i][u]
            if u:
                run = chunk[j:i] + run
            else:
                if run:
                    out.append(run)
                run = ""
                out.append(chunk[j:i])
            i, u = j, before
        if run:
            out.append(run)
        if len(self.memo) > 100_000:
            self.memo.clear()
        self.memo[chunk] = got = tuple(reversed(out))
        return got

    def words(self, host: str, path: str) -> list[str]:
        chunks = _CHUNK.findall(host.lower()) + _CHUNK.findall(path.lower())
        return [w for c in chunks if c not in STRIP for w in self.segment(c)]

    def log_odds(self, host: str, path: str) -> float:
        """Above zero: block."""
        return self.bias + sum(self.weight.get(w, 0.0) for w in self.words(host, path))


def parts(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a url."""
    has = F.coalesce(F.instr(url, "://") > 0, F.lit(False))
    rest = F.when(has, F.expr("substring(url, instr(url, '://') + 3)")).otherwise(F.lit(""))
    raw = F.regexp_extract(rest, "^[^/?#]*", 0)
    path = F.regexp_extract(F.substr(rest, F.length(raw) + 1), "^[^?#]*", 0)
    return F.translate(raw, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def rule_of(rules=RULES) -> tuple[Column, Column]:
    """The longest rule that fits columns host and path, and its verdict; null where none does."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for said, host, path in sorted(rules, key=lambda r: (len(r[1] + r[2]), [-ord(c) for c in r[1] + r[2]])):
        fits = ((F.col("host") == host) | F.col("host").endswith("." + host)) & F.col("path").startswith(path)
        rule, verdict = F.when(fits, F.lit(host + path)).otherwise(rule), F.when(fits, F.lit(said)).otherwise(verdict)
    return rule, verdict


def judge(pages: DataFrame, rules=RULES, blocked: str = BLOCKED_NAMES, allowed: str = ALLOWED_NAMES, counts: dict[str, int] | None = None) -> DataFrame:
    """page_id, host, path, rule, verdict, score (log odds of the method; null under a rule).

    ``counts``: the dictionary's words; by default those of the pages' own texts.
    """
    if counts is None:
        counts = corpus_words(pages) if "html" in pages.columns else {}
    shared = pages.sparkSession.sparkContext.broadcast(counts)  # VOCABULARY words at most
    split = pages.select("page_id", "url")
    host, path = parts(F.col("url"))
    split = split.select("page_id", host.alias("host"), path.alias("path"))
    rule, verdict = rule_of(rules)
    ruled = split.select("page_id", "host", "path", rule.alias("rule"), verdict.alias("verdict"))

    def run(batches) -> Iterator:
        import pyarrow as pa

        model = NameModel(blocked, allowed, counts=shared.value)
        for batch in batches:
            said, score = [], []
            for h, p, v in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), batch.column(4).to_pylist(), strict=True):
                odds = None if v else model.log_odds(h, p)
                score.append(odds)
                said.append(v or ("block" if odds > 0 else "allow"))
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(4)), pa.array(said, pa.string()), pa.array(score, pa.float64())], names=["page_id", "host", "path", "rule", "verdict", "score"])

    page_id = dict(pages.dtypes)["page_id"]
    return ruled.mapInArrow(run, f"page_id {page_id}, host string, path string, rule string, verdict string, score double")


def op4_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query over all pages."""
    return judge(spark.read.parquet(f"{sf_dir}/pages.parquet")).select("page_id", "host", "path", "rule", "verdict")
