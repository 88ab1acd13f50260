"""Scratch tables, as in the rest of the library."""

from ..scratch import delete, discard, new_path, release, shared_dir, written

__all__ = ["delete", "discard", "new_path", "release", "shared_dir", "written"]
