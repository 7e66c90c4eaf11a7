"""Tables an operator needs more than once; see the shared module."""

from ..sources.scratch import deal_by_range, delete, new_path, release, scratch_root, small_batches, small_side, write_table

__all__ = ["deal_by_range", "delete", "new_path", "release", "scratch_root", "small_batches", "small_side", "write_table"]
