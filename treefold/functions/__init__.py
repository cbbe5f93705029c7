"""Column functions and numeric kernels."""

from .columns import cents, clamp_add, knuth_parent, original_id, tag_of, tagged

__all__ = ["cents", "clamp_add", "knuth_parent", "original_id", "tag_of", "tagged"]
