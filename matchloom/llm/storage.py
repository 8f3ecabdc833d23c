"""Written tables in the shared folder; see matchloom.storage."""

from ..storage import Scratch, shared_dir

__all__ = ["Scratch", "shared_dir"]
