"""Intermediate tables of the operators: the library's own, see ``tabletext.storage``."""

from ..storage import mark, partitions_for, release, shared_folder, written

__all__ = ["mark", "partitions_for", "release", "shared_folder", "written"]
