"""All registered queries of the index, its baselines and experiments, and their SQL.

``queries()`` maps names to functions (spark, sf_dir) -> DataFrame, ``oracle_sql()`` names to SQL over the given tables.
"""

from apcube.queries.registry import ORACLES, QUERIES


def _load() -> None:
    from apcube.queries import baselines, experiments, methods, streams, surroundings  # noqa: F401


def queries():
    _load()
    return dict(QUERIES)


def oracle_sql():
    _load()
    return dict(ORACLES)
