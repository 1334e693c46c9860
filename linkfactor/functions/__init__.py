"""Column expressions and registered functions."""

from .expressions import bf16, bf16_parts, cosine, dot, hash_bucket, hash_unit, norm, packed_index, start_value

__all__ = ["bf16", "bf16_parts", "cosine", "dot", "hash_bucket", "hash_unit", "norm", "packed_index", "start_value"]
