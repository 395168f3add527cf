"""Digests, tags and deterministic authenticated encryption as column expressions, and the compositions they are compared with.

The tag of a value is HMAC-SHA-256. Sealing is in the manner of synthetic initial values: the tag names the
pair and keys the cipher, so equal values give equal pairs and nothing is added to the value's length. The
cipher is the counter keystream of the GCM mode: its header and its own tag are cut off, as our tag
authenticates the value.

Secret keys stand in no expression, so plans, event logs and user interfaces do not show them: what is
keyed is an Arrow function that holds the key in its closure. The cipher runs in the JVM under a key that
such a function derives from the tag.
"""

from __future__ import annotations

import hmac

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..params import StoreParams

BLOCK = 64


def pads(key: bytes) -> tuple[bytes, bytes]:
    k = key.ljust(BLOCK, b"\0")
    return bytes(x ^ 0x36 for x in k), bytes(x ^ 0x5C for x in k)


def digest_expr(v: Column) -> Column:
    return F.unhex(F.sha2(v, 256))


def hmac_expr(v: Column, key: bytes) -> Column:
    """HMAC-SHA-256 of a value; null for null."""

    @F.arrow_udf("binary")
    def keyed(v: pa.Array) -> pa.Array:
        return pa.array([None if x is None else hmac.digest(key, x, "sha256") for x in v.to_pylist()], pa.binary())

    return keyed(v)


def mac_expr(v: Column, p: StoreParams) -> Column:
    return hmac_expr(v, p.mac_key)


def tag_expr(v: Column, p: StoreParams) -> Column:
    """What a node is stored under."""
    return digest_expr(v) if p.protect == "hash" else mac_expr(v, p)


def _keystream(v: Column, tag: Column, p: StoreParams) -> Column:
    iv = F.substring(tag, 1, 12)
    out = F.aes_encrypt(v, hmac_expr(tag, p.cipher_key), F.lit("GCM"), F.lit("DEFAULT"), iv)
    return F.substring(out, F.lit(13), F.octet_length(v))


def seal_expr(v: Column, tag: Column, p: StoreParams) -> Column:
    """The stored bytes of a value."""
    return _keystream(v, tag, p) if p.protect == "siv" else v


def open_expr(c: Column, tag: Column, p: StoreParams) -> Column:
    """The value under a tag, not yet verified: the keystream undoes itself."""
    return _keystream(c, tag, p) if p.protect == "siv" else c


def verify_expr(v: Column, tag: Column, p: StoreParams) -> Column:
    """Whether a value belongs under its tag."""
    return tag_expr(v, p) == tag


def opened_expr(c: Column, tag: Column, p: StoreParams) -> Column:
    """The verified value, or null."""
    v = open_expr(c, tag, p)
    return F.when(verify_expr(v, tag, p), v)


COMPOSITIONS = ("aead_random", "encrypt_then_mac", "mac_then_encrypt", "encrypt_and_mac", "whole_deterministic")


def compose(values: DataFrame, mode: str, p: StoreParams) -> DataFrame:
    """(key, value) of plain values under another composition of encryption and authentication.

    aead_random: nonce and tag stored with the value, under its plain digest; encrypt_then_mac: the tag of a
    randomised ciphertext is the key; mac_then_encrypt: the tag is encrypted along, at random; encrypt_and_mac:
    the tag of the plain value is the key of a randomised ciphertext; whole_deterministic: sealed like ours.
    """
    v, key = F.col("value"), hmac_expr(F.lit(b"composition"), p.cipher_key)
    random = F.aes_encrypt(v, key, F.lit("GCM"))
    if mode == "aead_random":
        return values.select(digest_expr(v).alias("key"), random.alias("value"))
    if mode == "encrypt_then_mac":
        return values.select(random.alias("value")).select(mac_expr(F.col("value"), p).alias("key"), "value")
    if mode == "mac_then_encrypt":
        return values.select(F.aes_encrypt(F.concat(mac_expr(v, p), v), key, F.lit("GCM")).alias("value")).select(digest_expr(F.col("value")).alias("key"), "value")
    if mode == "encrypt_and_mac":
        return values.select(mac_expr(v, p).alias("key"), random.alias("value"))
    if mode == "whole_deterministic":
        q = p.with_(protect="siv")
        return values.select(mac_expr(v, p).alias("key"), v.alias("value")).select("key", seal_expr(F.col("value"), F.col("key"), q).alias("value"))
    raise ValueError(f"unknown composition {mode!r}")


def register_functions(spark: SparkSession, p: StoreParams) -> None:
    """SQL functions mac(v), seal(v) and unseal(k, v): inlined by the optimizer. The key shows in plans; use it with redaction, or a test key."""
    inner, outer = (x.hex() for x in pads(p.mac_key))
    c_in, c_out = (x.hex() for x in pads(p.cipher_key))
    mac = lambda v, i, o: f"unhex(sha2(concat(X'{o}', unhex(sha2(concat(X'{i}', {v}), 256))), 256))"
    stream = lambda v, k: f"substring(aes_encrypt({v}, {mac(k, c_in, c_out)}, 'GCM', 'DEFAULT', substring({k}, 1, 12)), 13, octet_length({v}))"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION mac(v BINARY) RETURNS BINARY RETURN {mac('v', inner, outer)}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION seal(v BINARY) RETURNS BINARY RETURN {stream('v', mac('v', inner, outer))}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION unseal(k BINARY, v BINARY) RETURNS BINARY RETURN {stream('v', 'k')}")
