"""Intermediate tables of the training-data operators, in the cluster's shared folder."""

from quadpost.sources.shared import drop, shared_dir, shuffle_parts, written

__all__ = ["drop", "shared_dir", "shuffle_parts", "written"]
