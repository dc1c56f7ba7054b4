"""Schemas of the tables that flow between the operators."""

from __future__ import annotations

from dataclasses import dataclass

INSTANCE = "cls string, source string, entity string, prop string, value string"
ALIGN = "cls string, source string, prop string, ref_prop string"
LEXICON = "word string, vec array<float>"
PAIR = "cls string, source_a string, prop_a string, source_b string, prop_b string"
LABELLED = PAIR + ", label int"
SIM = PAIR + ", score double, is_match boolean"
CLUSTER = "cls string, source string, prop string, cluster_id string"
RUNMETRIC = (
    "experiment string, dataset string, method string, config string, fraction double, run int, train_set string, "
    "tp long, fp long, fn long, tn long, precision double, recall double, f1 double"
)

PAIR_KEY = ["cls", "source_a", "prop_a", "source_b", "prop_b"]
PROPERTY_KEY = ["cls", "source", "prop"]

ORIGINS = ("instances", "names", "both")
KINDS = ("embedding", "non_embedding", "all")


@dataclass(frozen=True)
class FeatureConfig:
    """Which features of a pair the classifier sees: their origin and whether they come from word vectors."""

    origin: str = "both"
    kind: str = "all"

    def __post_init__(self) -> None:
        if self.origin not in ORIGINS or self.kind not in KINDS:
            raise ValueError(f"unknown feature configuration {self.origin}/{self.kind}")

    @property
    def name(self) -> str:
        return f"{self.origin}/{self.kind}"

    def slices(self, d: int) -> list[tuple[int, int]]:
        """Ranges of the whole vector: 28 format features, 1 number, d of values, d of names, 8 name distances."""
        value, name, dist = 29, 29 + d, 29 + 2 * d
        out = []
        if self.origin != "names" and self.kind != "embedding":
            out.append((0, 29))
        if self.origin != "names" and self.kind != "non_embedding":
            out.append((value, name))
        if self.origin != "instances" and self.kind != "non_embedding":
            out.append((name, dist))
        if self.origin != "instances" and self.kind != "embedding":
            out.append((dist, dist + 8))
        return out

    def width(self, d: int) -> int:
        return sum(b - a for a, b in self.slices(d))


CONFIGS = [FeatureConfig(o, k) for o in ORIGINS for k in KINDS]
