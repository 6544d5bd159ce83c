"""All named queries of the library proper."""

from __future__ import annotations

from rgsketch.queries import applications, engine, sketches, streams


def entries() -> dict:
    return {**sketches.queries(), **applications.queries(), **engine.queries(), **streams.queries()}
