"""All queries of the library, each with the SQL that checks it where SQL can."""

from __future__ import annotations

from relmix.catalogue import algebra, models, serving, surrounding


def queries() -> dict:
    return algebra.QUERIES | models.QUERIES | serving.QUERIES | surrounding.QUERIES


def oracle_sql() -> dict:
    return algebra.SQL | models.SQL | serving.SQL | surrounding.SQL
