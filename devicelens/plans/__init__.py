"""Registered queries and the inputs they share."""


def load() -> tuple[dict, dict]:
    """All queries and their oracle texts."""
    from devicelens.plans import deployment, live, methods, registry, surface, surrounding  # noqa: F401

    return registry.QUERIES, registry.ORACLE_SQL
