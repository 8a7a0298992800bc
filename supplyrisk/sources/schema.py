"""Types of build histories and packed vertex ids.

A vertex id is a LONG: four bits say what it is, the others are its key, so ids of
different kinds never meet and joins never compare strings. A fetched copy's key is made
of the copied artifact (kind and key) and the storage host, in widths that follow from the
largest host key; a key that does not fit fails the query. Histories whose keys do not fit
together number their copies instead (sources/build.py).
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

VERTICES = "vid long not null, vtype string not null, akey string, props map<string,string>"
EDGES = "eid long, src long, dst long, label string, props map<string,string>"
SEEDS = "vid long, kind string, from_ts timestamp, to_ts timestamp, score double, source string"
VERTEX_TYPES = ("artifact", "step", "host", "env")
SEED_KINDS = ("SV", "SM", "HV", "HM")

KEY_BITS = 59
#: Least width of a host key in a copy's id.
HOST_BITS = 21

# What the four top bits of a packed id say.
BASE, RELEASE, COPY, STEP, ENV, STORAGE, BUILDER, DOCUMENT, PAGE, WEB_HOST, SOURCE_HOST, TURN, CHAIN_STEP, CHAIN_ENV, CHAIN_HOST = range(1, 16)


def _fits(key: Column, bits: int, packed: Column, what: str) -> Column:
    """packed where the key fits its bits, null where it is null; otherwise the query fails."""
    error = F.raise_error(F.concat(F.lit(f"{what} does not fit {bits} bits: "), key.cast("string"))).cast("long")
    return F.when(key.isNull(), F.lit(None).cast("long")).when((key >= 0) & (key < F.lit(1 << bits)), packed).otherwise(error)


def pack(code: int, key: Column) -> Column:
    key = key.cast("long")
    return _fits(key, KEY_BITS, F.lit(code << KEY_BITS).cast("long").bitwiseOR(key), "key")


def hashed(code: int, name: Column) -> Column:
    """Id of a named thing: 59 bits of its hash."""
    return F.lit(code << KEY_BITS).cast("long").bitwiseOR(F.xxhash64(F.coalesce(name, F.lit(""))).bitwiseAND(F.lit((1 << KEY_BITS) - 1)))


def code_of(vid: Column) -> Column:
    return F.shiftrightunsigned(vid, KEY_BITS).cast("int")


def key_of(vid: Column) -> Column:
    return vid.bitwiseAND(F.lit((1 << KEY_BITS) - 1))


def pack_copy(artifact: Column, host_key: Column, host_bits: int = HOST_BITS) -> Column:
    """Copy of a base artifact or release at a storage host."""
    artifact_bits = KEY_BITS - host_bits - 1
    kind, host_key = (code_of(artifact) - BASE).cast("long"), host_key.cast("long")
    key = F.shiftleft(kind, artifact_bits).bitwiseOR(key_of(artifact))
    packed = F.lit(COPY << KEY_BITS).cast("long").bitwiseOR(F.shiftleft(key, host_bits).bitwiseOR(host_key))
    return _fits(host_key, host_bits, _fits(key_of(artifact), artifact_bits, packed, "artifact key"), "host key")


def copied_artifact(copy: Column, host_bits: int = HOST_BITS) -> Column:
    artifact_bits = KEY_BITS - host_bits - 1
    key = F.shiftrightunsigned(key_of(copy), host_bits)
    code = F.shiftrightunsigned(key, artifact_bits) + BASE
    return F.shiftleft(code, KEY_BITS).bitwiseOR(key.bitwiseAND(F.lit((1 << artifact_bits) - 1)))


def copy_host(copy: Column, host_bits: int = HOST_BITS) -> Column:
    return key_of(copy).bitwiseAND(F.lit((1 << host_bits) - 1))
