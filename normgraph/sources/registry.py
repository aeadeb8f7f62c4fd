"""Vocabulary and cue registries: small YAML files read on the driver, checked, and turned into rows."""

from __future__ import annotations

from functools import lru_cache
from pathlib import Path

import yaml
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader

FOLDER = Path(__file__).resolve().parent.parent / "registries"
#: Registries are broadcast; a larger one must be joined by shuffle instead.
MAX_ROWS = 100_000
SCHEMA = "domain string, kind string, name string, iri string, alias string, domain_class string, value_range string"


@lru_cache
def load(name: str) -> dict:
    return yaml.safe_load((FOLDER / f"{name}.yaml").read_text())


def rows(name: str) -> list[tuple]:
    """One row for each alias of each class and property, canonical names included."""
    spec = load(name)
    domain = spec["domain"]
    out = []
    known = {c["name"] for c in spec["classes"]}
    for c in spec["classes"]:
        out += [(domain, "class", c["name"], f"urn:{domain}:{c['name']}", a, None, None) for a in dict.fromkeys([c["name"], *c.get("synonyms", [])])]
    for p in spec["properties"]:
        if p["class"] not in known:
            raise ValueError(f"{p['name']}: no class {p['class']}")
        out += [(domain, "property", p["name"], f"urn:{domain}:{p['name']}", a, p["class"], p["range"]) for a in dict.fromkeys([p["name"], *p.get("synonyms", [])])]
    seen: dict[tuple, str] = {}
    for r in out:
        if seen.setdefault((r[1], r[4]), r[2]) != r[2]:
            raise ValueError(f"alias {r[4]} names {seen[(r[1], r[4])]} and {r[2]}")
    if len(out) > MAX_ROWS:
        raise ValueError(f"registry {name} has {len(out)} aliases; the broadcast bound is {MAX_ROWS}")
    return out


def load_registry(spark: SparkSession, name: str) -> DataFrame:
    return spark.createDataFrame(rows(name), SCHEMA)


@lru_cache
def cues(name: str) -> tuple[tuple[str, str], ...]:
    """(cue, operator), longest first, then in the order of the file."""
    items = load("cues")[name]
    return tuple((c["cue"], c["op"]) for c in sorted(items, key=lambda c: -len(c["cue"].split())))


class RegistrySource(DataSource):
    """``spark.read.format("vocabulary_registry").option("name", "star")``."""

    @classmethod
    def name(cls) -> str:
        return "vocabulary_registry"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema):  # noqa: ANN001
        return _Reader(rows(self.options["name"]))


class _Reader(DataSourceReader):
    def __init__(self, found: list[tuple]):
        self.found = found

    def read(self, partition):  # noqa: ANN001
        yield from self.found
