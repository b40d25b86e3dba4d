"""Projection runs, manifests, scope-local replacement, recovery, generations and rolling backlog."""

from __future__ import annotations

import hashlib
import json
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evigraph.operators import links as L
from evigraph.plans.store import path_for, written

CONTRACT = "projector-1"


def run_id(facts: str, rules: list[L.LinkRule], config: dict, contract: str = CONTRACT) -> str:
    """A run is named by all it depends on."""
    body = json.dumps({"config": config, "contract": contract, "facts": facts, "rules": sorted(r.rule_id() for r in rules)}, sort_keys=True)
    return hashlib.sha256(body.encode()).hexdigest()


def fingerprint(df: DataFrame, *keys: str) -> DataFrame:
    """One row that changes with any id of a set and not with its order."""
    return df.agg(F.count("*").alias("n"), F.coalesce(F.bit_xor(F.xxhash64(*keys)), F.lit(0)).alias("fingerprint"))


LINKS = "link_id string, scope long, src long, dst long, relation string, tag string, severity string, basis string, rule_id string, score long, link_us long, run_id string, attempt string"
STATE = "scope long, watermark long, generation string, run_id string, attempt string, seq long"
MANIFEST = "run_id string, generation string, projection string, facts string, config string, config_hash string, contract string, rule_ids array<string>, seq long"
ACTIVE = "generation string, seq long"
FAILURES = "scope long, target string, error string, at long"


class Store:
    """Derived links under attempts of runs, and the pointer rows by which readers see exactly one attempt
    a scope.

    An attempt's links are written first, then its manifest, then one ``state`` row per scope; a reader
    joins the newest state row, so an attempt that was cut short stays invisible, a run that is published
    again replaces itself, and nothing is updated in place. Pointer rows are numbered on from what the
    store holds, so a store that is opened again goes on where it was."""

    def __init__(self, spark: SparkSession, root: str | None = None):
        self.spark, self.root = spark, root or path_for(spark, "store")

    def _read(self, name: str, schema: str) -> DataFrame:
        from evigraph.sources.pack import exists

        path = f"{self.root}/{name}"
        return self.spark.read.schema(schema).parquet(path) if exists(self.spark, path) else self.spark.createDataFrame([], schema)

    def _append(self, name: str, rows: DataFrame) -> None:
        rows.write.mode("append").parquet(f"{self.root}/{name}")

    def _next(self, name: str, schema: str, column: str = "seq") -> int:
        return 1 + (self._read(name, schema).agg(F.max(column)).first()[0] or 0)

    def links(self) -> DataFrame:
        """Links of every scope's current attempt."""
        return self._read("links", LINKS).join(self.state().select("scope", "attempt"), ["scope", "attempt"]).drop("attempt")

    def history(self) -> DataFrame:
        """All pointer rows."""
        return self._read("state", STATE)

    def state(self) -> DataFrame:
        """The pointer row of each scope: the highest watermark, then the newest."""
        return self.history().groupBy("scope").agg(F.max_by(F.struct("watermark", "generation", "run_id", "attempt", "seq"), F.struct("watermark", "seq", "attempt")).alias("s")).select("scope", "s.*")

    def manifests(self) -> DataFrame:
        """One row for each published run; one that was published again shows once."""
        return self._read("manifest", MANIFEST).dropDuplicates(["run_id"])

    def publish(self, derived: DataFrame, scopes: DataFrame, generation: str, run: str, manifest: DataFrame | None = None) -> None:
        """scopes: (scope, watermark) that the run covers, also those without links."""
        attempt, seq = uuid.uuid4().hex, self._next("state", STATE)
        self._append("links", derived.withColumns({"run_id": F.lit(run), "attempt": F.lit(attempt)}))
        if manifest is not None:
            self._append("manifest", manifest.withColumn("seq", F.lit(seq).cast("long")))
        self._append("state", scopes.select("scope", "watermark", F.lit(generation).alias("generation"), F.lit(run).alias("run_id"), F.lit(attempt).alias("attempt"), F.lit(seq).cast("long").alias("seq")))

    def activate(self, generation: str) -> None:
        """Point readers' target at a generation; one that no manifest names is refused."""
        if not self.manifests().filter(F.col("generation") == generation).limit(1).count():
            raise ValueError(f"no manifest of generation {generation}")
        self._append("active", self.spark.createDataFrame([(generation, self._next("active", ACTIVE))], ACTIVE))

    def active(self) -> str | None:
        r = self._read("active", ACTIVE).agg(F.max_by("generation", "seq")).first()
        return r[0]

    def progress(self, scopes: DataFrame) -> DataFrame:
        """(generation, scopes): how many stand at each generation; the pointer does not tell that."""
        return scopes.select("scope").join(self.state().select("scope", "generation"), "scope", "left").groupBy("generation").agg(F.count("*").alias("scopes"))

    def failed(self, scopes: DataFrame, target: str, error: str) -> None:
        at = self._next("failures", FAILURES, "at")
        self._append("failures", scopes.select("scope", F.lit(target).alias("target"), F.lit(error).alias("error"), F.lit(at).cast("long").alias("at")))

    def failures(self) -> DataFrame:
        return self._read("failures", FAILURES)

    def compacted(self) -> Store:
        """A new store of the live links, the newest pointers and all manifests; dead attempts are left
        behind."""
        new = Store(self.spark)
        new._append("links", self._read("links", LINKS).join(self.state().select("scope", "attempt"), ["scope", "attempt"], "left_semi"))
        new._append("state", self.state().select("scope", "watermark", "generation", "run_id", "attempt", "seq"))
        for name, schema in (("manifest", MANIFEST), ("active", ACTIVE), ("failures", FAILURES)):
            new._append(name, self._read(name, schema))
        return new


def facts_of(tags: DataFrame, scopes: DataFrame) -> str:
    """A name for the facts a run reads: the content of its tags, and the scopes with their watermarks."""
    parts = [fingerprint(tags, *sorted(tags.columns)).first(), fingerprint(scopes, "scope", "watermark").first()]
    return ":".join(f"{p['n']}.{p['fingerprint']}" for p in parts)


def manifest_row(spark: SparkSession, run: str, generation: str, projection: str, facts: str, rules: list[L.LinkRule], config: dict) -> DataFrame:
    """What a run depends on, enough to tell whether it can be run again."""
    text = json.dumps(config, sort_keys=True)
    row = (run, generation, projection, facts, text, hashlib.sha256(text.encode()).hexdigest(), CONTRACT, sorted(r.rule_id() for r in rules), 0)
    return spark.createDataFrame([row], MANIFEST).drop("seq")


def project_scopes(store: Store, tags: DataFrame, scopes: DataFrame, rules: list[L.LinkRule], generation: str, mode: str = "both") -> str:
    """Recompute and replace the whole link set of ``scopes`` (scope, watermark); others are untouched."""
    own = tags.join(scopes.select("scope"), "scope", "left_semi")
    facts, config = facts_of(own, scopes), {"mode": mode, "generation": generation}
    run = run_id(facts, rules, config)
    store.publish(L.project(own, rules, run, mode), scopes, generation, run, manifest_row(store.spark, run, generation, "links", facts, rules, config))
    return run


def reproduce(store: Store, run: str, tags: DataFrame, rules: list[L.LinkRule]) -> DataFrame:
    """The links of an earlier run, derived again from what its manifest names. Refused if the code's
    contract, a rule or the facts are not those of the run. ``rules`` may hold more than the run used;
    ``tags`` are the facts as of then."""
    m = store.manifests().filter(F.col("run_id") == run).first()
    if m is None:
        raise ValueError(f"no manifest of run {run}")
    used = [r for r in rules if r.rule_id() in m["rule_ids"]]
    if m["contract"] != CONTRACT or len(used) != len(m["rule_ids"]):
        raise ValueError("the run's contract or rules are not at hand")
    scopes = store.history().filter(F.col("run_id") == run).select("scope", "watermark").distinct()
    own = tags.join(scopes.select("scope"), "scope", "left_semi")
    if run_id(facts_of(own, scopes), used, json.loads(m["config"])) != run:
        raise ValueError("the facts are not those of the run")
    return L.project(own, used, run, json.loads(m["config"])["mode"])


def institution(spark: SparkSession, root: str, name: str) -> Store:
    """An institution's own generations and links over the shared facts."""
    return Store(spark, f"{root}/institution-{name}")


def mismatched(packed: DataFrame, state: DataFrame) -> DataFrame:
    """Scopes whose stored watermark and projected watermark differ, either way or on one side only."""
    j = packed.select("scope", F.col("watermark").alias("stored")).join(state.select("scope", F.col("watermark").alias("projected")), "scope", "full_outer")
    return j.filter(~F.col("stored").eqNullSafe(F.col("projected")))


def recover(store: Store, tags: DataFrame, packed: DataFrame, rules: list[L.LinkRule], generation: str) -> DataFrame:
    """Catch up exactly the inconsistent scopes; returns them."""
    late = written(mismatched(packed, store.state()).filter("stored is not null"))
    project_scopes(store, tags, late.select("scope", F.col("stored").alias("watermark")), rules, generation)
    return late


# rolling generations

CLASSES = {1: "new write", 2: "recent", 3: "inactive", 4: "deceased"}


def priority(scopes: DataFrame, horizon_us: int, years: int = 3) -> DataFrame:
    """scopes (scope, last_us, deceased, new_write) with class: a new write goes first, then recent
    activity; what is not known counts as recent."""
    since = horizon_us - years * 31_557_600_000_000
    c = F.when(F.coalesce("new_write", F.lit(False)), 1).when(F.coalesce("deceased", F.lit(False)), 4).when(F.col("last_us").isNull() | (F.col("last_us") >= since), 2).otherwise(3)
    return scopes.withColumn("class", c)


def backlog(scopes: DataFrame, state: DataFrame, target: str) -> DataFrame:
    """Scopes not at the target generation; nothing is queued, the filter is the queue."""
    return scopes.join(state.filter(F.col("generation") == target).select("scope"), "scope", "left_anti")


def page(classed: DataFrame, n: int) -> DataFrame:
    """The next page: class first, then a fixed hash order."""
    return classed.orderBy("class", F.sha2(F.col("scope").cast("string"), 256)).limit(n)


def drain(store: Store, tags: DataFrame, scopes: DataFrame, rules: list[L.LinkRule], target: str, size: int, fail: Callable[[DataFrame], str | None] | None = None, tries: int = 3) -> list[tuple[int, int]]:
    """Project page after page until the backlog is empty. The scopes of a page that fails are noted with
    the error and wait; once the others are done they are tried again, ``tries`` times in all. Returns
    (class, scopes) per page in the order drained; scopes that keep failing stay in the backlog."""
    done = []
    for _ in range(tries):
        waiting = None
        while True:
            left = backlog(scopes, store.state(), target)
            if waiting is not None:
                left = left.join(waiting, "scope", "left_anti")
            p = written(page(left, size))
            n = p.count()
            if not n:
                break
            error = fail(p) if fail is not None else None
            if error:
                store.failed(p, target, error)
                waiting = p.select("scope") if waiting is None else written(waiting.unionByName(p.select("scope")))
                continue
            project_scopes(store, tags, p, rules, target)
            done.append((p.agg(F.min("class")).first()[0], n))
        if waiting is None:
            break
    return done


def retry_latest(failures: DataFrame) -> DataFrame:
    """Latest attempt of each failed scope, with the attempts so far."""
    return failures.groupBy("scope").agg(F.count("*").alias("attempts"), F.max_by("error", "at_us").alias("error"), F.max("at_us").alias("at_us"))


def access(scopes: DataFrame, state: DataFrame, target: str, policy: str) -> DataFrame:
    """What a reader of a scope gets while it awaits the target generation."""
    s = scopes.join(state.select("scope", "generation"), "scope", "left")
    late = {"allow_prior": "prior", "project_on_access": "project", "deny_high_risk": "deny"}[policy]
    return s.withColumn("decision", F.when(F.col("generation") == target, "current").when(F.col("generation").isNull() & (F.lit(policy) == "allow_prior"), "project").otherwise(late))


def lint_lineage(df: DataFrame, allowed: list[str]) -> list[str]:
    """Leaf files of a plan that are not source tables: capsules may be built from nothing else."""
    return sorted(f for f in df.inputFiles() if not any(f"/{a}.parquet" in f for a in allowed))
