"""Intermediate tables in the folder that the cluster shares.

Lineage is cut by writing Parquet below `spark.checkpoint.dir`: a lost executor then costs a reread,
never a recomputation of the whole history.
"""

from __future__ import annotations

from ..shared import Workspace, shared_folder, unused

__all__ = ["Workspace", "shared_folder", "unused"]
