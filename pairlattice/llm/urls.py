"""URL filters: rules by host and path, then a naive Bayes verdict on segmented host and path words.

Concatenated names ("cheappills") are split by a unigram Viterbi search over a public word list whose
ranks give Zipf probabilities; a multinomial naive Bayes model, fitted on labelled phrases, scores
the words.  Parts that only say how an address is built (``www``, ``com``, ``html``, languages) are no evidence.

Defined results: host and path are empty for a null url or one without ``://``; words that the model
has not seen carry no evidence, so a url without known words gets the prior's verdict; repeated rows
each get a row; an empty table gives none; further columns are ignored; very long hosts and paths are
processed whole (the search is linear in their length).
"""

from __future__ import annotations

import json
import math
import re
from collections import Counter
from collections.abc import Iterator, Sequence

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Rules (host with path prefix, verdict).
RULES = (("org/", "allow"), ("example.org/es/", "block"), ("example.org/en/1", "block"), ("com/fr/", "allow"), ("com/de/", "block"))

# Words by topic, the labelled list that the classifier learns from; none is taken from a table.
TOPICS = {
    "block": (
        "casino poker jackpot slots roulette betting bets bet bookmaker blackjack baccarat wager odds bingo lottery gamble gambling spins win wins",
        "pills viagra cialis pharmacy tablets steroids opioid xanax tramadol slimming meds cheap cheapest painkillers erection",
        "porn xxx sex adult nude nudes cams escort escorts hot singles hookup erotic fetish babes naked strip",
        "payday loans loan cash advance debt instant approval quick refinance bailout lender",
        "replica replicas fake counterfeit watches handbags knockoff imitation luxury outlet discount buy",
        "malware trojan virus keylogger ransomware exploit phishing hacked hacker botnet stealer spyware download downloads",
        "torrent torrents warez crack cracked cracks keygen serial pirate pirated nulled leaked",
        "ads ad adverts banner banners popup popups click clicks tracker track tracking redirect affiliate pixel",
        "spam spammer spammy farm backlinks backlink links link bulk mailer bots traffic doorway",
        "prize prizes winner free giveaway lucky claim bonus reward rewards millionaire doubler forex miracle scam scams",
    ),
    "allow": (
        "school schools university college teacher student students lesson lessons course courses library education exam campus learning",
        "science research laboratory physics chemistry biology astronomy theory experiment journal paper papers math mathematics geology",
        "health hospital doctor nurse clinic medicine patient nutrition wellness dental therapy surgery care vaccine heart",
        "news daily herald times report reports press editor politics world article articles opinion weather today magazine",
        "travel hotel hotels flight flights guide tour tours beach mountain airport train city map maps holiday journey",
        "food recipe recipes kitchen cooking bread cake dinner restaurant vegetable garden soup coffee tea baking chef",
        "government council ministry parliament law court police tax public service services agency department election mayor citizen",
        "software code computer developer engineering open source data server network linux python documentation docs help manual",
        "football soccer tennis basketball cycling running league team club match stadium athletics swimming hockey coach",
        "art museum gallery music concert theatre film cinema painting poetry novel book books author dance history",
        "home house furniture design architecture garden tools repair paint wood family children parents baby pets",
        "nature river forest ocean animal animals bird birds tree trees climate energy water earth wildlife park",
        "business company office bank finance market industry insurance trade economy career jobs team contact about",
        "shop store product products catalog price prices order delivery fashion shoes clothing books toys bicycle",
        "community forum church charity volunteer association society foundation group events meeting member members culture village",
        "photo photos camera video radio television podcast game games puzzle chess hobby craft knitting model",
    ),
}
#: Parts of hosts and paths that say how an address is built, not what it is about.
STRUCTURE = frozenset("www m mobile blog web site com net org edu gov info html htm php asp index page pages id ref utm en de fr es it nl pl pt uk us example localhost http https".split())


def phrases_of(topics: dict[str, Sequence[str]] = TOPICS) -> dict[str, list[list[str]]]:
    """Labelled phrases by a rule: each word of a topic with the two that follow it, around the end."""
    return {label: [[w[i], w[(i + 1) % len(w)], w[(i + 2) % len(w)]] for t in lines for w in [t.split()] for i in range(len(w))] for label, lines in topics.items()}


LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
LONGEST_WORD = 24


def default_words() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def word_scores(path: str | None = None) -> dict[str, float]:
    """Log probability of each whole word of the public vocabulary, by the Zipf law of its rank."""
    with open(path or default_words()) as f:
        vocab = json.load(f)["model"]["vocab"]
    ranked = [w[:-4] for w, _ in sorted(vocab.items(), key=lambda x: x[1]) if w.endswith("</w>") and w[:-4].isalpha() and (len(w) > 6 or w[:-4] in ("a", "i"))]
    ranked = [w for w in ranked if len(w) <= LONGEST_WORD]
    total = math.log(sum(1 / (r + 2) for r in range(len(ranked))))
    return {w: -math.log(r + 2) - total for r, w in enumerate(ranked)}


def segment(name: str, scores: dict[str, float], unknown: float = -14.0) -> list[str]:
    """Best split of a lower-case name; a character outside every word costs ``unknown``; unknown runs come back whole."""
    n = len(name)
    best, back = [0.0] + [-math.inf] * n, [0] * (n + 1)
    for end in range(1, n + 1):
        for start in range(max(0, end - LONGEST_WORD), end):
            s = scores.get(name[start:end])
            if s is None:
                if start != end - 1:
                    continue
                s = unknown
            if best[start] + s > best[end]:
                best[end], back[end] = best[start] + s, start
    out, end, run = [], n, ""
    while end:
        start = back[end]
        w = name[start:end]
        if w in scores:
            if run:
                out.append(run)
                run = ""
            out.append(w)
        else:
            run = w + run
        end = start
    if run:
        out.append(run)
    return out[::-1]


class NaiveBayes:
    """Multinomial, add-one smoothing over the words seen in training; others carry no evidence."""

    def __init__(self, phrases: dict[str, Sequence[Sequence[str]]], good: str = "allow", bad: str = "block"):
        self.counts = {k: Counter(w for p in v for w in p) for k, v in phrases.items()}
        self.vocab = set().union(*self.counts.values())
        totals = {k: sum(c.values()) + len(self.vocab) for k, c in self.counts.items()}
        n = {k: len(v) for k, v in phrases.items()}
        self.prior = math.log(n[bad] / n[good])
        self.evidence = {w: math.log((self.counts[bad][w] + 1) / totals[bad]) - math.log((self.counts[good][w] + 1) / totals[good]) for w in self.vocab}

    def log_odds(self, words: Sequence[str]) -> float:
        return self.prior + math.fsum(self.evidence.get(w, 0.0) for w in words)


def parts(url: Column) -> tuple[Column, Column]:
    """(host, path) of a url."""
    pattern = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    host = F.coalesce(F.regexp_extract(url, pattern, 1), F.lit(""))
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.coalesce(F.regexp_extract(url, pattern, 2), F.lit(""))


def rule_of(host: Column, path: Column, rules: Sequence[tuple[str, str]] = RULES) -> Column:
    """The longest fitting rule, else null; the first given wins among equals."""
    out = F.lit(None).cast("string")
    for rule, _ in sorted(reversed(rules), key=lambda r: len(r[0])):
        h, p = rule[: rule.index("/")], rule[rule.index("/") :]
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        out = F.when(fits, F.lit(rule)).otherwise(out)
    return out


def judge(pages: DataFrame, rules: Sequence[tuple[str, str]] = RULES, phrases: dict[str, Sequence[Sequence[str]]] | None = None, words: str | None = None, threshold: float = 0.0) -> DataFrame:
    """(page_id, host, path, rule, verdict, log_odds, words); one narrow pass that reads the url only."""
    scores, phrases = word_scores(words), phrases or phrases_of()
    model = NaiveBayes(phrases)
    for w in model.vocab:  # each word of a phrase is a word
        scores.setdefault(w, -11.0)
    host, path = parts(F.col("url"))
    kind = dict(pages.dtypes)["page_id"]
    given = dict(rules)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, list[str]] = {}

        def split(name: str) -> list[str]:
            if name not in seen:
                if len(seen) > 200_000:
                    seen.clear()
                seen[name] = segment(name, scores)
            return seen[name]

        for batch in batches:
            found, odds, verdicts = [], [], []
            for h, p, rule in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                ws = [w for name in re.findall(r"[^\W\d_]+", f"{h} {p}".translate(LOWER)) if name not in STRUCTURE for w in split(name) if w not in STRUCTURE]
                x = model.log_odds(ws)
                found.append(ws)
                odds.append(x)
                verdicts.append(given[rule] if rule is not None else "block" if x > threshold else "allow")
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(4)), pa.array(verdicts, pa.string()), pa.array(odds, pa.float64()), pa.array(found, pa.list_(pa.string()))], names=["page_id", "host", "path", "rule", "verdict", "log_odds", "words"])

    cols = pages.select("page_id", host.alias("host"), path.alias("path"))
    return cols.withColumn("rule", rule_of(F.col("host"), F.col("path"), rules)).mapInArrow(run, f"page_id {kind}, host string, path string, rule string, verdict string, log_odds double, words array<string>")
