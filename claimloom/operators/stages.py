"""Generation stages over an offline provider: grounding, outline, article, lint, execution modes, cost."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import links, tokens
from .crawl import TAU_CONFIDENCE, committed

TARGET_WORDS = 716
Provider = Callable[[pd.DataFrame], pd.Series]


@dataclass(frozen=True)
class StageConfig:
    model: str = "rules"
    temperature: float = 0.0
    max_tokens: int = 2048


@dataclass(frozen=True)
class RunConfig:
    """regime: general or topic; strategy: baseline or calibrated. A topic run has a root subject and may have a persona."""

    regime: str = "general"
    strategy: str = "baseline"
    grounding: bool = True
    reasoning: bool = False
    persona: str | None = None
    root: str | None = None
    stages: dict[str, StageConfig] = field(default_factory=dict)

    def __post_init__(self) -> None:
        if self.regime not in ("general", "topic") or self.strategy not in ("baseline", "calibrated"):
            raise ValueError("regime is general or topic, strategy is baseline or calibrated")
        if self.regime == "topic" and self.root is None:
            raise ValueError("a topic run needs a root subject")

    @property
    def tau(self) -> float | None:
        return TAU_CONFIDENCE if self.strategy == "calibrated" else None

    def stage(self, name: str) -> StageConfig:
        return self.stages.get(name, StageConfig())

    def carried(self, subjects: DataFrame) -> DataFrame:
        """subjects with the run's constants as columns; every later stage keeps them."""
        return subjects.withColumns({"regime": F.lit(self.regime), "strategy": F.lit(self.strategy), "persona": F.lit(self.persona).cast("string"), "root": F.lit(self.root).cast("string")})


def run_stage(requests: DataFrame, provider: Provider, mode: str = "online", cap: int = 8) -> DataFrame:
    """requests (request, prompt, ...) with the provider's answer column.

    online: at most cap calls run at a time, in Arrow batches. batch: requests are submitted as a written table and their
    answers joined back on the request. Both give the same answers; a request without one has null.
    """
    schema = "request string, answer string"

    def call(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({"request": b["request"], "answer": provider(b)})

    if mode == "online":
        answers = requests.select("request", "prompt").repartition(cap, "request").mapInPandas(call, schema)
    elif mode == "batch":
        answers = committed(committed(requests.select("request", "prompt"), "submitted").mapInPandas(call, schema), "answered")
    else:
        raise ValueError(f"mode is online or batch, not {mode}")
    return requests.join(answers, "request", "left")


FACTS = "array<struct<fact:string,confidence:double>>"


def grounded(answers: DataFrame, tau: float = TAU_CONFIDENCE) -> DataFrame:
    """The fact sheet of each answer (JSON): facts at tau or above; a broken answer gives an empty sheet."""
    facts = F.coalesce(F.from_json("answer", FACTS), F.array().cast(FACTS))
    return answers.withColumn("facts", F.filter(facts, lambda f: f.confidence >= tau)).drop("answer")


def outline_ok(sections: Column, root: Column | None = None, least: int = 6, most: int = 7) -> Column:
    """6 to 7 headings, one of which names the root in a topic run."""
    size = F.size(sections).between(least, most)
    return size if root is None else size & (root.isNull() | F.exists(sections, lambda h: F.contains(F.lower(h), F.lower(root))))


def rule_facts(b: pd.DataFrame) -> pd.Series:
    """Offline provider: a fact for each word of the prompt, its confidence from the word's length."""
    import json

    return b["prompt"].map(lambda p: json.dumps([{"fact": w, "confidence": min(1.0, 0.5 + len(w) / 16)} for w in (p or "").split()]))


def rule_outline(b: pd.DataFrame) -> pd.Series:
    """Offline provider: six headings, the last of which names the prompt."""
    return b["prompt"].map(lambda p: "|".join(["Overview", "Origins", "Structure", "Uses", "Reception", f"Relation to {p}"]))


def articles(outlines: DataFrame, strategy: str = "baseline") -> DataFrame:
    """Wiki markup from subject, sections and facts: a bold lead and a section with a link for each fact, scored if calibrated."""
    score = F.lit("") if strategy == "baseline" else F.lit(" (0.80)")
    link = F.transform("facts", lambda f: F.concat(F.lit("[["), f.fact, score, F.lit("]]")))
    body = F.array_join(F.transform("sections", lambda h: F.concat(F.lit("\n== "), h, F.lit(" ==\nIt is told here.\n"))), "")
    lead = F.concat(F.lit("'''"), F.col("subject"), F.lit("''' is a subject. It has facts. "), F.array_join(link, ", "), F.lit(".\n"))
    return outlines.withColumn("wikitext", F.concat(lead, body))


# Allowed numbers of links by regime, for well-known and lesser-known subjects.
LINK_BANDS = {"general": ((50, 100), (15, 30)), "topic": ((30, 50), (8, 15))}


def lint(articles: DataFrame, regime: str = "general", target: int = TARGET_WORDS, slack: float = 0.5) -> DataFrame:
    """articles (key, subject, wikitext, sections) with a flag for each instruction that the text does not keep.

    headings: not the outline in order; lead: not 2 to 4 sentences; n_links: outside both bands; dense: a sentence with more
    than five links; self_link; umbrella: more than three one-word lower-case targets; reference: URLs or ref tags; length:
    further from the target than slack allows.
    """
    text = F.col("wikitext")
    head = F.transform(F.regexp_extract_all(text, F.lit(r"(?m)^==+\s*([^=\n]+?)\s*==+\s*$"), F.lit(1)), F.trim)
    lead = F.regexp_extract(text, r"(?s)^(.*?)(?:\n==|\z)", 1)
    sentence = F.filter(F.split(lead, r"[.!?]+(?:\s+|\z)"), lambda x: F.trim(x) != "")
    target_of = F.transform(links(text), lambda x: x.target)
    (a, b), (c, e) = LINK_BANDS[regime]
    n = F.size(target_of)
    words = F.size(tokens(text))
    return articles.withColumns(
        {
            "flag_headings": ~F.coalesce(head == F.col("sections"), F.lit(False)),
            "flag_lead": ~F.size(sentence).between(2, 4),
            "flag_n_links": ~(n.between(a, b) | n.between(c, e)),
            "flag_dense": F.exists(F.split(text, r"[.!?]+\s+"), lambda x: F.size(F.regexp_extract_all(x, F.lit(r"(\[\[)"), F.lit(1))) > 5),
            "flag_self_link": F.exists(target_of, lambda x: F.lower(x) == F.lower(F.col("subject"))),
            "flag_umbrella": F.size(F.filter(target_of, lambda x: x.rlike(r"^[a-z]+$"))) > 3,
            "flag_reference": text.rlike(r"(?i)https?://|<ref"),
            "flag_length": F.abs(words - target) > slack * target,
        }
    )


def cost(log: DataFrame, prices: DataFrame, grounding_share: float = 0.33) -> DataFrame:
    """log: (stage, calls, tokens); prices: (stage, per_1k) of few rows. Cost of both modes and with grounding; batch calls cost half."""
    c = log.join(prices, "stage").withColumn("online", F.col("tokens") / 1000 * F.col("per_1k"))
    return c.withColumns({"batch": F.col("online") / 2, "online_grounded": F.col("online") * (1 + grounding_share)})


def per_million(total: Column, articles: Column) -> Column:
    return 1_000_000 * total / F.nullif(articles, F.lit(0))
