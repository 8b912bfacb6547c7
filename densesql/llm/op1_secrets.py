"""Secret scans with corpus-wide ownership frequency.

Every text is scanned once for three base kinds and for generic live-looking tokens.
Candidate values are hashed; the hashes are counted over all documents by distinct
owner and repository.  A value that many owners hold is a widely copied example (a
manual's sample key); one that few owners hold is owner-specific.  Base spans always
stay; a generic token becomes a span only where its value is owner-specific.

Defined results: a null or empty text has no span; a null owner or repository counts
as one more owner or repository; repeated rows give one result row each; other
columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.llm.common import documents, map_rows
from densesql.plans.staging import Staging

# The base patterns and the least length of what they catch.
ASSIGN = r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ASSIGN_LEAST, ACCESS_LEAST, HEX_LEAST = 12, 18, 16
KINDS = ("assign", "access", "hex", "generic")

#: Values held by at most so many owners are owner-specific.
MAX_OWNERS = 2
#: A generic token has at least so many characters and bits of entropy per character.
GENERIC_LEAST, GENERIC_BITS = 20, 3.0

FOUND = "owner string, repo string, doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans array<struct<kind:int,start:long,end:long,hash:string>>"


def entropy(value: str) -> float:
    """Shannon entropy of a string's characters in bits."""
    return -sum(n / len(value) * math.log2(n / len(value)) for n in Counter(value).values())


def looks_live(value: str) -> bool:
    """Mixed case and digits, and no simple repetition: more like a key than like a word."""
    classes = (r"[0-9]", r"[a-z]", r"[A-Z]")
    return all(re.search(c, value) for c in classes) and entropy(value) >= GENERIC_BITS


def base_spans(text: str) -> list[tuple[int, int, int, str]]:
    """(start, kind, end, value) of the base kinds, by start and then kind."""
    assign, access, hexes = _patterns()[:3]
    found = [(m.start(), 0, m.end(), m[2]) for m in assign.finditer(text) if len(m[2]) >= ASSIGN_LEAST]
    found += [(m.start(), 1, m.end(), m[0]) for m in access.finditer(text)]
    found += [(m.start(), 2, m.end(), m[0]) for m in hexes.finditer(text)]
    return sorted(found)


def _patterns() -> tuple[re.Pattern, ...]:
    """Compiled patterns (``re`` keeps them).

    A run that is too short is dropped whole, and a longer run starts at its first
    character, so the least length of the last two can stand in the pattern.
    """
    return (
        re.compile(ASSIGN, re.IGNORECASE | re.ASCII),
        re.compile(rf"AKIA[A-Z0-9]{{{ACCESS_LEAST - 4},}}"),
        re.compile(rf"[0-9a-f]{{{HEX_LEAST},}}"),
        re.compile(rf"(?<![A-Za-z0-9_-])[A-Za-z0-9_-]{{{GENERIC_LEAST},}}+"),
    )


def render(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[kind]}:{start}:{end}" for start, kind, end in sorted(spans))


def _digest(value: str) -> str:
    return hashlib.blake2b(value.encode("utf-8", "surrogatepass"), digest_size=16).hexdigest()


def scan(docs: DataFrame, owner: str, repo: list[str]) -> DataFrame:
    """Per document: base counts and digest, and all candidate spans with hashed values."""

    def make() -> Callable:
        generic = _patterns()[3]

        def step(owners, ids, texts, *repos):
            for k, text in enumerate(texts):
                text = text or ""
                base = base_spans(text)
                more = []
                for m in generic.finditer(text):
                    if looks_live(m[0]) and not any(s < m.end() and m.start() < e for s, _, e, _ in base):
                        more.append((m.start(), 3, m.end(), m[0]))
                kinds = Counter(x[1] for x in base)
                digest = hashlib.sha256(render([x[:3] for x in base]).encode()).hexdigest()
                spans = [{"kind": c, "start": s, "end": e, "hash": _digest(v)} for s, c, e, v in sorted(base + more)]
                where = "/".join("\0" if r[k] is None else str(r[k]) for r in repos)
                yield owners[k], where, ids[k], kinds[0], kinds[1], kinds[2], digest, spans

        return step

    return map_rows(docs, [owner, "doc_id", "text", *repo], FOUND, make)


def ownership(candidates: DataFrame) -> DataFrame:
    """(hash, n_owners, n_repos): distinct holders of each hashed value over the whole corpus."""
    null = F.lit("\0")
    held = candidates.select("hash", F.coalesce("owner", null).alias("owner"), F.coalesce("repo", null).alias("repo"))
    by_repo = held.groupBy("hash", "owner", "repo").agg(F.count(F.lit(1)).alias("n_uses"))
    by_owner = by_repo.groupBy("hash", "owner").agg(F.count(F.lit(1)).alias("n_repos"), F.sum("n_uses").alias("n_uses"))
    return by_owner.groupBy("hash").agg(
        F.count(F.lit(1)).alias("n_owners"), F.sum("n_repos").alias("n_repos"), F.sum("n_uses").alias("n_uses")
    )


def find_secrets(docs: DataFrame, owner: str = "source", repo: tuple[str, ...] = ("source", "lang"), max_owners: int = MAX_OWNERS) -> DataFrame:
    """One row per document: base counts and digest, all spans, and how its values are held."""
    staging = Staging(docs.sparkSession, "secrets")
    found = staging.table(scan(docs, owner, list(repo)), "found", row_id="row_id")
    kept = ["row_id", "doc_id", "n_assign", "n_access", "n_hex", "base_sha256"]
    each = found.where(F.size("spans") > 0).select(*kept, "owner", "repo", F.inline("spans"))
    judged = each.join(ownership(each), "hash").withColumn("specific", F.col("n_owners") <= max_owners)
    is_span = (F.col("kind") < 3) | F.col("specific")
    name = F.element_at(F.array(*map(F.lit, KINDS)), F.col("kind") + 1)
    part = F.struct("start", "kind", F.concat_ws(":", name, F.col("start"), F.col("end")).alias("shown"))
    listed = judged.groupBy(*kept).agg(
        F.array_join(F.transform(F.array_sort(F.collect_list(F.when(is_span, part))), lambda x: x["shown"]), ",").alias("spans"),
        F.count_if("specific").alias("n_owner_specific"),
        F.count_if(~F.col("specific")).alias("n_widely_copied"),
    )
    zero = F.lit(0).cast("long")
    bare = found.where(F.size("spans") == 0).select(*kept, F.lit("").alias("spans"), zero.alias("n_owner_specific"), zero.alias("n_widely_copied"))
    return listed.unionByName(bare).drop("row_id")


def op1_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_secrets(documents(spark, sf_dir))
