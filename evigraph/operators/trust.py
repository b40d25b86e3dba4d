"""Attestations: Ed25519 statements, purposes, trust policy, approvals, releases."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType

#: The three purposes; none stands for another.
PURPOSES = ("clinical_origin", "exchange_import", "knowledge_release")

# fixed values of the curve (RFC 8032)
P = 2**255 - 19
ORDER = 2**252 + 27742317777372353535851937790883648493
D = -121665 * pow(121666, P - 2, P) % P
ROOT = pow(2, (P - 1) // 4, P)


def _add(a, b):
    x = (a[1] - a[0]) * (b[1] - b[0]) % P
    y = (a[1] + a[0]) * (b[1] + b[0]) % P
    z, t = 2 * a[2] * b[2] % P, 2 * a[3] * b[3] * D % P
    e, f, g, h = y - x, z - t, z + t, y + x
    return e * f % P, g * h % P, f * g % P, e * h % P


def _times(k: int, point):
    out = (0, 1, 1, 0)
    while k:
        if k & 1:
            out = _add(out, point)
        point, k = _add(point, point), k >> 1
    return out


def _recover(y: int, sign: int):
    if y >= P:
        return None
    x2 = (y * y - 1) * pow(D * y * y + 1, P - 2, P) % P
    x = pow(x2, (P + 3) // 8, P)
    if (x * x - x2) % P:
        x = x * ROOT % P
    if (x * x - x2) % P or not x and sign:
        return None
    x = P - x if x & 1 != sign else x
    return x, y, 1, x * y % P


BASE = _recover(4 * pow(5, P - 2, P) % P, 0)


def _pack(point) -> bytes:
    z = pow(point[2], P - 2, P)
    x, y = point[0] * z % P, point[1] * z % P
    return (y | (x & 1) << 255).to_bytes(32, "little")


def _unpack(b: bytes):
    n = int.from_bytes(b, "little")
    return _recover(n & (1 << 255) - 1, n >> 255) if len(b) == 32 else None


def _secret(seed: bytes) -> tuple[int, bytes]:
    h = hashlib.sha512(seed).digest()
    return int.from_bytes(h[:32], "little") & (1 << 254) - 8 | 1 << 254, h[32:]


def public_key(seed: bytes) -> bytes:
    return _pack(_times(_secret(seed)[0], BASE))


def _challenge(*parts: bytes) -> int:
    return int.from_bytes(hashlib.sha512(b"".join(parts)).digest(), "little") % ORDER


def sign(seed: bytes, message: bytes) -> bytes:
    a, prefix = _secret(seed)
    r = _challenge(prefix, message)
    head = _pack(_times(r, BASE))
    s = (r + _challenge(head, public_key(seed), message) * a) % ORDER
    return head + s.to_bytes(32, "little")


def verify_one(key: bytes, message: bytes, signature: bytes) -> bool:
    a, r = _unpack(key), _unpack(signature[:32])
    s = int.from_bytes(signature[32:], "little")
    if a is None or r is None or len(signature) != 64 or s >= ORDER:
        return False
    left, right = _times(s, BASE), _add(r, _times(_challenge(signature[:32], key, message), a))
    return (left[0] * right[2] - right[0] * left[2]) % P == 0 and (left[1] * right[2] - right[1] * left[2]) % P == 0


@F.pandas_udf(BooleanType())
def signature_ok(key: pd.Series, message: pd.Series, signature: pd.Series) -> pd.Series:
    seen: dict[tuple, bool] = {}
    out = []
    for k, m, s in zip(key, message, signature, strict=True):
        t = (k, m, s)
        if t not in seen:
            seen[t] = bool(k and s) and verify_one(bytes.fromhex(k), (m or "").encode(), bytes.fromhex(s))
        out.append(seen[t])
    return pd.Series(out)


@dataclass(frozen=True)
class Key:
    key_id: str
    organization: int
    public: str
    purposes: tuple[str, ...]
    tenants: tuple[int, ...]
    valid_from: int = 0
    valid_to: int = 1 << 62
    revoked_us: int | None = None


def statement(subject: str, purpose: str, organization: int, actor: str, signed_us: int) -> str:
    """The canonical text that is signed; the subject's id is in it and stays unchanged."""
    return f'{{"actor":"{actor}","organization":{organization},"purpose":"{purpose}","signed_us":{signed_us},"subject":"{subject}"}}'


def attest(subject: str, purpose: str, key: Key, seed: bytes, actor: str, signed_us: int) -> tuple:
    if purpose not in PURPOSES:
        raise ValueError(purpose)
    s = statement(subject, purpose, key.organization, actor, signed_us)
    return subject, purpose, key.organization, actor, key.key_id, signed_us, s, sign(seed, s.encode()).hex()


ATTESTATION = "subject string, purpose string, organization int, actor string, key_id string, signed_us long, statement string, signature string"
KEYS = "key_id string, key_org int, public string, purposes array<string>, tenants array<int>, valid_from long, valid_to long, revoked_us long"


def key_table(spark, keys: list[Key]) -> DataFrame:
    return spark.createDataFrame([(k.key_id, k.organization, k.public, list(k.purposes), list(k.tenants), k.valid_from, k.valid_to, k.revoked_us) for k in keys], KEYS)


def policy_verdict(attestations: DataFrame, keys: DataFrame, tenant: int) -> DataFrame:
    """The policy part of the verdict; the first failing test names it. A key inside an attestation is
    never used: only the policy's own keys count."""
    j = attestations.join(F.broadcast(keys), "key_id", "left")
    return j.withColumn("verdict", (
        F.when(F.col("key_org").isNull(), "unknown_key").when(F.col("key_org") != F.col("organization"), "organization").when(~F.array_contains("tenants", tenant), "tenant")
        .when(~F.array_contains("purposes", F.col("purpose")), "purpose").when((F.col("signed_us") < F.col("valid_from")) | (F.col("signed_us") >= F.col("valid_to")), "validity")
        .when(F.col("revoked_us") <= F.col("signed_us"), "revoked").otherwise("valid")
    ))


def verify(attestations: DataFrame, keys: DataFrame, tenant: int) -> DataFrame:
    """Verdicts with signatures checked for those that pass the policy."""
    v = policy_verdict(attestations, keys, tenant)
    said = F.format_string('{"actor":"%s","organization":%d,"purpose":"%s","signed_us":%d,"subject":"%s"}', "actor", "organization", "purpose", "signed_us", "subject")
    v = v.withColumn("verdict", F.when((F.col("verdict") == "valid") & (said != F.col("statement")), "subject").otherwise(F.col("verdict")))
    good = v.filter("verdict = 'valid'")
    good = good.withColumn("verdict", F.when(signature_ok("public", "statement", "signature"), "valid").otherwise("signature"))
    return v.filter("verdict <> 'valid'").unionByName(good)


def by_purpose(attestations: DataFrame, purpose: str) -> DataFrame:
    return attestations.filter(F.col("purpose") == purpose)


def of_subject(attestations: DataFrame) -> DataFrame:
    return attestations.groupBy("subject").agg(F.array_sort(F.collect_set("organization")).alias("organizations"), F.count("*").alias("n"))


def approved(verified: DataFrame, purpose: str, required: int) -> DataFrame:
    """(subject, approvals, approved): distinct organizations with a valid attestation of the purpose."""
    return verified.filter((F.col("verdict") == "valid") & (F.col("purpose") == purpose)).groupBy("subject").agg(F.count_distinct("organization").alias("approvals")).withColumn("approved", F.col("approvals") >= required)


def effective_policy(org_tenant: DataFrame) -> DataFrame:
    """Tenants each organization's keys may act for; ids decide, names are snapshots."""
    return org_tenant.groupBy("organization").agg(F.array_sort(F.collect_set("tenant")).alias("tenants"))


def author_and_signer(attestations: DataFrame) -> DataFrame:
    return attestations.select("subject", F.col("actor").alias("author"), F.col("organization").alias("signer"))


def revalidate(rules: DataFrame, approvals: DataFrame) -> DataFrame:
    """(rule_id, active, reason): at start a rule is active only if its body still hashes to its id and
    its release has the approvals; anything else is inactive."""
    j = rules.join(approvals.withColumnRenamed("subject", "rule_id"), "rule_id", "left")
    reason = F.when(F.sha2("body", 256) != F.col("rule_id"), "tampered").when(F.col("approved").isNull() | ~F.col("approved"), "approvals").otherwise("ok")
    return j.select("rule_id", (reason == "ok").alias("active"), reason.alias("reason"))


def startup(rules: DataFrame, attestations: DataFrame, keys: DataFrame, tenant: int, required: int, at_us: int) -> DataFrame:
    """Revalidation at ``at_us``: approvals are counted anew from attestations whose keys are neither expired
    nor revoked by then, whatever held when they were signed; a rule that falls short is inactive."""
    now = keys.filter((F.col("valid_to") > at_us) & (F.col("revoked_us").isNull() | (F.col("revoked_us") > at_us)))
    return revalidate(rules, approved(verify(attestations, now, tenant), "knowledge_release", required))


# the JVM's own signatures, for the few that the driver makes or checks
# fixed values: the encodings that stand before a raw public and a raw private key
_PUBLIC, _PRIVATE = bytes.fromhex("302a300506032b6570032100"), bytes.fromhex("302e020100300506032b657004220420")


def jvm_sign(spark, seed: bytes, message: bytes) -> bytes:
    java = spark._jvm.java.security
    key = java.KeyFactory.getInstance("Ed25519").generatePrivate(java.spec.PKCS8EncodedKeySpec(_PRIVATE + seed))
    s = java.Signature.getInstance("Ed25519")
    s.initSign(key)
    s.update(message)
    return bytes(s.sign())


def jvm_verify(spark, public: bytes, message: bytes, signature: bytes) -> bool:
    java = spark._jvm.java.security
    try:
        s = java.Signature.getInstance("Ed25519")
        s.initVerify(java.KeyFactory.getInstance("Ed25519").generatePublic(java.spec.X509EncodedKeySpec(_PUBLIC + public)))
        s.update(message)
        return bool(s.verify(signature))
    except Exception:  # noqa: BLE001  what is no key or no signature does not verify
        return False
