"""The package's shared-folder tables, under the name that the corpus operators use."""

from __future__ import annotations

from ..workspace import Workspace, shared_folder, ship

__all__ = ["Workspace", "shared_folder", "ship"]
