"""Intermediate tables in the folder that driver and executors share."""

from gradsift.sources.staging import Stage, shared_dir

__all__ = ["Stage", "shared_dir"]
