"""Readers, writers and the session helpers that every plan shares."""

from taskmesh.sources.storage import TABLES, discard, load, materialise, register_views, relieve, shared_dir, ship_package

__all__ = ["TABLES", "discard", "load", "materialise", "register_views", "relieve", "shared_dir", "ship_package"]
