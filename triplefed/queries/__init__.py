"""The library's queries by name, and the SQL that checks them."""

from __future__ import annotations


def all_queries() -> tuple[dict, dict]:
    """The quick ones first: sessions and experiments come last."""
    from triplefed.queries import methods, sessions, surface

    found, checks = {}, {}
    for module in (methods, surface, sessions):
        q, o = module.queries()
        found |= q
        checks |= o
    return found, checks
