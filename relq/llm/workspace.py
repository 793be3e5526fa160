"""Shared tables, as the rest of the library keeps them."""

from relq.plans.workspace import Workspace, shared_dir

__all__ = ["Workspace", "shared_dir"]
