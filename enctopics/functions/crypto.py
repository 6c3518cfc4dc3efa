"""Encryption as column expressions: equal tokens have equal handles, equal documents have different envelopes."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Kinds of encryption that may and may not be used for tokens, which have to be found again by equality.
DETERMINISTIC, PROBABILISTIC = {"keyed-hash", "siv", "deterministic-rsa"}, {"gcm", "cbc-random-iv", "elgamal", "paillier"}


def mac_pads(key: str) -> tuple[bytes, bytes]:
    """What a keyed digest (HMAC with SHA-256) puts before the message and before the inner digest."""
    raw = key.encode()
    raw = hashlib.sha256(raw).digest() if len(raw) > 64 else raw
    block = raw.ljust(64, b"\0")
    return bytes(x ^ 0x36 for x in block), bytes(x ^ 0x5C for x in block)


def handle(token: Column, key: str) -> Column:
    """A keyed digest that stands for a token in the cloud."""
    inner, outer = (F.lit(bytearray(x)) for x in mac_pads(key))
    return F.sha2(F.concat(outer, F.unhex(F.sha2(F.concat(inner, token.cast("binary")), 256))), 256)


def _key(key: str) -> Column:
    return F.unhex(F.substring(F.sha2(F.lit(f"seal{key}"), 256), 1, 32))


def seal(token: Column, key: str) -> Column:
    """An envelope that the key opens; its nonce comes from the token, so equal tokens have equal envelopes."""
    nonce = F.unhex(F.substring(F.sha2(F.concat(F.lit(f"nonce{key}"), token), 256), 1, 24))
    return F.aes_encrypt(token, _key(key), F.lit("GCM"), F.lit("DEFAULT"), nonce)


def open_(sealed: Column, key: str) -> Column:
    return F.aes_decrypt(sealed, _key(key), F.lit("GCM"), F.lit("DEFAULT")).cast("string")


def seal_document(text: Column, key: str) -> Column:
    """An envelope with a random nonce: equal texts can't be told to be equal."""
    return F.aes_encrypt(text, _key(key), F.lit("GCM"), F.lit("DEFAULT"))


def require_deterministic(scheme: str) -> str:
    if scheme not in DETERMINISTIC:
        raise ValueError(f"tokens need an encryption with equal results for equal tokens, such as {sorted(DETERMINISTIC)}, not {scheme!r}")
    return scheme
