"""DuckDB SQL that gives the same rows as the queries of ``codeprov.queries``."""

from __future__ import annotations

from codeprov.queries import MODULES

SQL: dict[str, str] = {k: s for m in MODULES for k, s in m.SQL.items()}
