"""Secret scan with corpus-wide ownership of each candidate.

Every text gives candidates: assignments, access keys and long hexadecimal runs (the base kinds), and some wider kinds (service
tokens, signed web tokens, private key headers, addresses with passwords). Each candidate's value is hashed and aggregated over the
corpus by distinct owners and repositories. A value that at least ``max_owners`` owners hold is an example that people copy, and so is
one that two owners hold in ``max_repos`` repositories together: it travels. A value of one owner is never an example, in however many
of their repositories it lies; it is taken as live, unless it is short and a placeholder. Base spans are always reported; wider ones
only while live. Ownership may be counted over another corpus than the one that is scanned: over the one before copies were dropped.

Edge cases: null text is empty; null owner or repository counts as one unnamed; a repeated row counts once in ownership and
is reported each time; extra columns, whatever their names, are ignored; an empty table gives an empty one. Offsets are code points.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import claim, salted_join, slices, stage, unused

SHORT = 40  # characters up to which a value may be a placeholder
#: Fixed patterns of the base kinds, with the group that holds the value and its least length.
BASE = (
    ("assign", re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII), 2, 6),
    ("access", re.compile(r"AKIA[A-Z0-9]+"), 0, 20),
    ("hex", re.compile(r"[0-9a-f]{24,}"), 0, 24),  # greedy runs of 24 at least are the greedy runs that are long enough
)
#: Wider kinds; reported only where ownership makes them live.
WIDE = (
    ("service", re.compile(r"\b(?:gh[pousr]_[A-Za-z0-9]{20,}|xox[abprs]-[A-Za-z0-9-]{10,}|[sr]k_(?:live|test)_[A-Za-z0-9]{16,}|AIza[A-Za-z0-9_-]{30,})"), 0, 10),
    ("webtoken", re.compile(r"\beyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}"), 0, 20),
    ("pem", re.compile(r"-----BEGIN [A-Z ]{0,30}PRIVATE KEY-----[A-Za-z0-9+/=\s]{40,}"), 0, 60),
    ("url", re.compile(r"[a-z][a-z0-9+.-]{1,15}://[^\s/:@]{1,64}:([^\s/:@]{6,64})@"), 1, 6),
)
KINDS = tuple(k for k, *_ in BASE + WIDE)
ORDER = {k: i for i, k in enumerate(KINDS)}
_ASSIGN_HINT = re.compile(r"passw|secret|token|api_?key", re.IGNORECASE | re.ASCII)


def candidates(text: str) -> list[tuple[str, int, int, str]]:
    """(kind, start, end, value) of a text, leftmost without overlap in each kind, by start and kind."""
    out = []
    for kind, pattern, group, least in BASE + WIDE:
        if kind == "access" and "AKIA" not in text or kind == "webtoken" and "eyJ" not in text or kind == "pem" and "-----BEGIN" not in text or kind == "url" and "://" not in text:
            continue
        for m in pattern.finditer(text):
            value = m.group(group)
            if len(value) >= least:
                out.append((kind, m.start(), m.end(), value))
    return sorted(out, key=lambda c: (c[1], ORDER[c[0]], c[2]))


def row_key() -> Column:
    """256 bits of a row's id and text."""
    return F.sha2(F.concat(F.coalesce(F.col("doc_id").cast("long").cast("string"), F.lit("")), F.lit(":"), F.coalesce(F.col("text"), F.lit(""))).cast("binary"), 256)


def placeholder(value: str) -> bool:
    """A short value with a word that stands for a secret; longer ones may hold such letters by chance."""
    low = value.lower()
    return len(value) <= SHORT and any(w in low for w in ("example", "changeme", "placeholder", "xxxx", "your_", "dummy", "sample"))


CAND = "array<struct<kind:string,start:bigint,end:bigint,value_hash:bigint,placeholder:boolean>>"
CAND_TYPE = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("value_hash", pa.int64()), ("placeholder", pa.bool_())]))


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    claim("secrets")
    base_kinds = [k for k, *_ in BASE]
    for batch in slices(batches):
        counts: list[list[int]] = [[] for _ in BASE]
        digest, cands = [], []
        for text in batch.column(1).to_pylist():
            found = candidates(text or "")
            base = [c for c in found if c[0] in base_kinds]
            for k, kind in enumerate(base_kinds):
                counts[k].append(sum(c[0] == kind for c in base))
            digest.append(hashlib.sha256(",".join(f"{k}:{s}:{e}" for k, s, e, _ in base).encode()).hexdigest())
            cands.append([{"kind": k, "start": s, "end": e, "value_hash": int.from_bytes(hashlib.sha256(v.encode()).digest()[:8], "little", signed=True), "placeholder": placeholder(v)} for k, s, e, v in found])
        yield pa.record_batch([batch.column(0), batch.column(2), batch.column(3), batch.column(4), *(pa.array(c, pa.int64()) for c in counts), pa.array(digest, pa.string()), pa.array(cands, CAND_TYPE)], names=["doc_id", "owner", "repo", "key", "n_assign", "n_access", "n_hex", "base_sha256", "cands"])


SCANNED = f"doc_id long, owner string, repo string, key string, n_assign long, n_access long, n_hex long, base_sha256 string, cands {CAND}"


def _scanned(docs: DataFrame, owner: Column, repo: Column | None) -> DataFrame:
    """Candidates of each row, with its owner and repository."""
    repo = F.concat_ws("/", owner.cast("string"), F.col("lang").cast("string")) if repo is None and "lang" in docs.columns else owner if repo is None else repo
    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text"), F.coalesce(owner.cast("string"), F.lit("")).alias("owner"), F.coalesce(repo.cast("string"), F.lit("")).alias("repo"), row_key().alias("key"))
    return picked.mapInArrow(_scan, SCANNED)


def ownership(found: DataFrame) -> DataFrame:
    """(value_hash, owners, repos) of each value that more than one owner or repository holds; ``found``: value_hash, owner, repo."""
    held = found.groupBy("value_hash", "owner", "repo").agg(F.lit(1).alias("one")).groupBy("value_hash", "owner").agg(F.count("*").alias("repos"))
    return held.groupBy("value_hash").agg(F.count("*").alias("owners"), F.sum("repos").alias("repos")).where((F.col("owners") > 1) | (F.col("repos") > 1))


def scan_secrets(docs: DataFrame, owner: Column | str = "source", repo: Column | None = None, max_owners: int = 4, max_repos: int = 8, corpus: DataFrame | None = None) -> DataFrame:
    """A row for each row of ``docs``: doc_id, counts and digest of the base kinds, ``spans`` (kind:start:end, comma-joined), n_live, n_example, ``found`` (array of kind, start, end, owners, repos, verdict), ``key`` (digest of id and text). Owners and repositories are counted in ``corpus`` (``docs`` if None)."""
    owner = F.col(owner) if isinstance(owner, str) else owner
    scanned = stage(_scanned(docs, owner, repo).withColumn("row", F.monotonically_increasing_id()), "secrets")
    flat = scanned.select("row", "owner", "repo", F.explode("cands").alias("c")).select("row", "owner", "repo", "c.*")
    everywhere = flat if corpus is None else _scanned(corpus, owner, repo).select("owner", "repo", F.explode("cands.value_hash").alias("value_hash"))
    judged = salted_join(flat, ownership(everywhere), ["value_hash"], "row", "left")
    owners, repos = F.coalesce("owners", F.lit(1)).cast("long"), F.coalesce("repos", F.lit(1)).cast("long")
    travels = (owners >= max_owners) | (owners > 1) & (repos >= max_repos)
    verdict = F.when(travels, "example").when(F.col("placeholder"), "plain").otherwise("live")
    judged = judged.select("row", "kind", "start", "end", owners.alias("owners"), repos.alias("repos"), verdict.alias("verdict"))
    judged = judged.where(F.col("kind").isin([k for k, *_ in BASE]) | (F.col("verdict") == "live"))
    rank = F.element_at(F.create_map(*[F.lit(x) for k, i in ORDER.items() for x in (k, i)]), F.col("kind"))
    by_row = judged.groupBy("row").agg(F.array_sort(F.collect_list(F.struct("start", rank.alias("rank"), "end", "kind", "owners", "repos", "verdict"))).alias("found"))
    found = F.coalesce("found", F.expr("array()").cast("array<struct<start:bigint,rank:int,end:bigint,kind:string,owners:bigint,repos:bigint,verdict:string>>"))
    out = scanned.drop("cands", "owner", "repo").join(by_row, "row", "left").withColumn("found", found)
    spans = F.concat_ws(",", F.transform("found", lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))))
    count = lambda v: F.size(F.filter("found", lambda x: x["verdict"] == v)).cast("long")
    return out.select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256", spans.alias("spans"), count("live").alias("n_live"), count("example").alias("n_example"), "found", "key")


def redact(text: str, spans: list[tuple[int, int]], mark: str = "[removed]") -> str:
    """The text with the union of some spans replaced."""
    out, at = [], 0
    for s, e in sorted(spans):
        if e <= at:
            continue
        if s >= at:
            out += [text[at:s], mark]
        at = e
    return "".join([*out, text[at:]])


def remove_live(docs: DataFrame, max_owners: int = 4, max_repos: int = 8, mark: str = "[removed]", corpus: DataFrame | None = None) -> DataFrame:
    """``docs`` with live secrets replaced in the text (n_chars follows); copied examples and all other rows stay as they are.
    Where ``docs`` have lost their copies, ``corpus`` is what still has them: ownership is counted there."""
    key, cut = unused(docs, "__key"), unused(docs, "__spans")
    live = F.filter("found", lambda x: x["verdict"] == "live")
    found = scan_secrets(docs, max_owners=max_owners, max_repos=max_repos, corpus=corpus).where("n_live > 0")
    spans = found.select(F.col("key").alias(key), F.transform(live, lambda x: F.array(x["start"], x["end"])).alias(cut)).dropDuplicates([key])
    schema = docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("secrets")
        for batch in slices(batches):
            texts, found = batch.column(text_at).to_pylist(), batch.column(batch.num_columns - 1).to_pylist()
            clean = [t if t is None or not s else redact(t, [tuple(x) for x in s], mark) for t, s in zip(texts, found, strict=True)]
            columns = []
            for i, f in enumerate(schema):
                old = batch.column(i)
                if i == text_at:
                    old = pa.array(clean, old.type)
                elif f.name == "n_chars":
                    old = pa.array([n if t is c else len(c) for n, t, c in zip(old.to_pylist(), texts, clean, strict=True)], old.type)
                columns.append(old)
            yield pa.record_batch(columns, names=schema.names)

    text_at = schema.names.index("text")
    return docs.withColumn(key, row_key()).join(spans, key, "left").select(*(F.col(f"`{c}`") for c in docs.columns), F.col(cut)).mapInArrow(run, schema)
