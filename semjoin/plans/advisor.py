"""Decisions: override, then a clear reply, then the fixed fallback; each one is on record."""

from __future__ import annotations

import dataclasses
import json

from pyspark.sql import DataFrame

from semjoin.functions.text import ENCODERS, STAND_INS, bottom_n
from semjoin.models import UNKNOWN, LanguageModel, Prompt, parse_choice, parse_list


#: Samples for decisions are drawn in another order than the workloads' rows.
SAMPLE_SEED = 100


@dataclasses.dataclass(frozen=True)
class JoinOptions:
    force_strategy: str | None = None
    embedding: str | None = None
    projection: str | None = None
    clustering: str | None = None
    labels: tuple[str, ...] | None = None
    label_table: bool = False
    multi_label: bool = False
    max_labels: int = 20
    block: tuple[int, int] = (15, 15)
    cluster_ratio: float = 0.05
    max_clusters: int = 1000
    filter_threshold: int = 5  # hundredths
    min_profile_size: int = 6
    profile_sample: int = 5
    pool_factor: int | None = 4
    centroid_top_m: int | None = None
    reuse_profile: bool = False
    advisor_sample: int = 10
    label_sample: int = 20
    classify_batch: int = 25
    project_batch: int = 25
    dedupe_text: bool = False
    kmeans_rounds: int = 5
    seed: int = 7
    buckets: int | None = None
    max_tokens: int | None = None
    single_call: bool = False


@dataclasses.dataclass(frozen=True)
class Decision:
    field: str
    raw: str | None
    value: str
    source: str  # override | advisor | fallback


#: Choices of each field and what a reply that names none or several falls back to.
CHOICES = {"strategy": ("cluster", "label"), "embedding": tuple(ENCODERS), "projection": ("off", "on"), "clustering": ("kmeans", "hdbscan")}


def choices(field: str) -> tuple[str, ...]:
    """Encoders can be registered at any time."""
    return tuple(ENCODERS) if field == "embedding" else CHOICES[field]


def resolve(field: str, raw: str | None, override: str | None = None) -> Decision:
    allowed = choices(field)
    if override is not None:
        return Decision(field, None, override, "override")
    choice = parse_choice(raw or "", allowed)
    return Decision(field, raw, choice or allowed[0], "advisor" if choice else "fallback")


class Advisor:
    """Asks the model about one join. Samples are taken once; each call is logged under stage advisor."""

    def __init__(self, a: DataFrame, b: DataFrame, predicate: str, model: LanguageModel, options: JoinOptions):
        self.a, self.b, self.predicate, self.model, self.options = a, b, predicate, model, options
        self.calls: list[tuple] = []
        self.decisions: list[Decision] = []
        self._samples: tuple | None = None
        self._answers: dict | None = None

    def _sample(self) -> tuple:
        if self._samples is None:
            n, seed = self.options.advisor_sample, self.options.seed + SAMPLE_SEED
            self._samples = tuple(tuple(r["text"] for r in bottom_n(x, n, seed).select("text").collect()) for x in (self.a, self.b))
        return self._samples

    def ask(self, kind: str, allowed: tuple[str, ...] = (), b: tuple[str, ...] | None = None, stage: str = "advisor") -> str:
        a, own_b = self._sample()
        schemas = ("A(id long, text string)", "B(id long, text string)")
        reply = self.model.complete(Prompt(kind, self.predicate, () if b is not None else a, own_b if b is None else b, allowed, schemas))
        self.calls.append((f"{stage}:{kind}", 1, self.model.name, len(a), len(own_b), reply.in_tok, reply.out_tok, "ok", stage))
        return reply.text

    def decide(self, field: str) -> str:
        override = self.options.force_strategy if field == "strategy" else getattr(self.options, field)
        raw = None if override is not None else self._all_at_once(field) if self.options.single_call else self.ask(field, choices(field))
        self.decisions.append(resolve(field, raw, override))
        return self.decisions[-1].value

    def _all_at_once(self, field: str) -> str:
        """One call for all fields; what it leaves out or garbles falls back field by field."""
        if self._answers is None:
            try:
                got = json.loads(self.ask("all", tuple(x for c in CHOICES for x in choices(c))))
            except ValueError:
                got = {}
            self._answers = got if isinstance(got, dict) else {}
        return str(self._answers.get(field, ""))

    def encoder(self) -> tuple[str, str]:
        """The encoder decided on, and the one that runs for it here."""
        name = self.decide("embedding")
        name = name if name in ENCODERS else CHOICES["embedding"][0]
        return name, STAND_INS.get(name, name)

    def labels(self) -> list[str]:
        if self.options.labels is not None:
            out = [*dict.fromkeys(x for x in self.options.labels if x != UNKNOWN), UNKNOWN]
            self.decisions.append(Decision("labels", None, ",".join(out), "override"))
            return out
        sample = tuple(r["text"] for r in bottom_n(self.b, self.options.label_sample, self.options.seed + SAMPLE_SEED).select("text").collect())
        raw = self.ask("labels", b=sample, stage="labels")
        out = parse_list(raw)
        self.decisions.append(Decision("labels", raw, ",".join(out), "advisor"))
        return out


def labels_are_valid(labels: list[str], n_sample: int, unknown_share: float = 0.0, max_labels: int = 20, max_unknown: float = 0.5) -> bool:
    """Two classes at least, max_labels at most, fewer than the rows they came from, few unknown rows."""
    n = len([x for x in labels if x != UNKNOWN])
    return 2 <= n <= max_labels and n < max(3, n_sample) and unknown_share <= max_unknown
