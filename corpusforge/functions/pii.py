"""Replacement of e-mail addresses and public IPv4 addresses; telephone numbers are left alone."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from corpusforge.functions.text import bound, bucket_of, col

EMAIL = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}"
#: What e-mail addresses become, and addresses that answer nobody for public IPs.
EMAILS = ("email@example.com", "firstname.lastname@example.org")
POOL = ("22.214.171.124", "126.96.36.199", "188.8.131.52", "184.108.40.206", "220.127.116.11", "18.104.22.168")
_OCTET = r"(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
QUAD = rf"\b{_OCTET}(?:\.{_OCTET}){{3}}\b"
#: Address blocks that are not globally routable.
PRIVATE = r"^(?:0\.|10\.|127\.|169\.254\.|192\.168\.|192\.0\.0\.|192\.0\.2\.|198\.1[89]\.|198\.51\.100\.|203\.0\.113\.|172\.(?:1[6-9]|2[0-9]|3[01])\.|100\.(?:6[4-9]|[7-9][0-9]|1[01][0-9]|12[0-7])\.|22[4-9]\.|23[0-9]\.|24[0-9]\.|25[0-5]\.)"


def _replaced(text: Column, pattern: str, by) -> Column:
    """Text with each match replaced by ``by(match)``: gaps and matches alternate."""
    gaps, found = F.split(text, pattern), F.regexp_extract_all(text, F.lit(pattern), 0)
    ends = F.concat(F.transform(found, by), F.array(F.lit("")))
    return F.when(text.rlike(pattern), F.array_join(F.zip_with(gaps, ends, lambda g, m: F.concat(g, m)), "")).otherwise(text)


def _pick(value: Column, pool: tuple[str, ...]) -> Column:
    return F.element_at(F.array(*[F.lit(x) for x in pool]), (bucket_of(value, len(pool)) + 1).cast("int"))


def emails(text: Column | str, replacements: tuple[str, ...] = EMAILS) -> Column:
    """E-mail addresses become one of the replacements, chosen by hash; replacements stay as they are."""
    return _replaced(col(text), EMAIL, lambda m: F.when(m.isin(*replacements), m).otherwise(_pick(m, replacements)))


def is_public(ip: Column) -> Column:
    return ~ip.rlike(PRIVATE)


def ips(text: Column | str, pool: tuple[str, ...] = POOL) -> Column:
    """Public IPv4 addresses become one of the pool, chosen by hash; private ones and the pool's own stay."""
    return _replaced(col(text), QUAD, lambda m: F.when(is_public(m) & ~m.isin(*pool), _pick(m, pool)).otherwise(m))


def apply(text: Column | str) -> Column:
    return bound(emails(text), lambda t: ips(t))


def counts(text: Column | str) -> Column:
    """How many e-mail addresses, public and other IPv4 addresses a text has."""
    quads = F.regexp_extract_all(col(text), F.lit(QUAD), 0)
    public = F.size(F.filter(quads, is_public))
    return F.struct(F.regexp_count(col(text), F.lit(EMAIL)).alias("email"), public.alias("ip"), (F.size(quads) - public).alias("private_ip"))
