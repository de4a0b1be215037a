"""Frontends make PATHS of a source; any function that does can be registered beside the built-in ones.

PATHS is ``fragment_id long, n_lines int, path_no int, nodes array<array<string>>, mult int``: a row is a path, a node is
its list of tokens.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame

COLUMNS = ("fragment_id", "n_lines", "path_no", "nodes", "mult")
_KNOWN: dict[str, Callable[..., DataFrame]] = {}


def register(name: str, make: Callable[..., DataFrame]) -> None:
    """``make(source, **options)`` returns PATHS; a name can be taken once."""
    if name in _built_in() or name in _KNOWN:
        raise ValueError(f"frontend {name!r} is there already")
    _KNOWN[name] = make


def names() -> list[str]:
    return sorted({**_built_in(), **_KNOWN})


def paths_of(name: str, source: DataFrame, **options) -> DataFrame:
    """PATHS of ``source`` by the named frontend, its columns checked."""
    out = {**_built_in(), **_KNOWN}[name](source, **options)
    missing = [c for c in COLUMNS if c not in out.columns]
    if missing:
        raise ValueError(f"frontend {name!r} makes no column {', '.join(missing)}")
    return out.select(*COLUMNS)


def _built_in() -> dict[str, Callable[..., DataFrame]]:
    from pathtwin.frontends import event_flow, java, tables, text_lines

    return {
        "lines": text_lines.line_paths, "paragraphs": text_lines.paragraph_paths, "words": text_lines.word_paths, "events": event_flow.flow_paths, "orders": tables.order_paths,
        "tags": tables.tag_paths, "pages": tables.dom_paths, "conversations": tables.conversation_paths, "methods": java.parse_methods,
    }
