"""Every registered query of the engine and its SQL equivalent."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from hushgrad.fl import queries as fl
from hushgrad.functions import sql as surface
from hushgrad.operators import around
from hushgrad.plans import methods, oracle
from hushgrad.sources import formats
from hushgrad.streaming import rounds

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {**methods.QUERIES, **fl.QUERIES, **around.QUERIES, **formats.QUERIES, **surface.QUERIES, **rounds.QUERIES}
ORACLE_SQL: dict[str, str] = {**oracle.SQL, **fl.SQL, **around.SQL, **formats.SQL, **surface.SQL, **rounds.SQL}
