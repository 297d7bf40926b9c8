"""User functions of the store, for DataFrames and SQL."""

from .udfs import codewords_udtf, dense_udtf, expand_blob, pack_text, register, size_of, sparse_udtf, substr_of

__all__ = ["codewords_udtf", "dense_udtf", "expand_blob", "pack_text", "register", "size_of", "sparse_udtf", "substr_of"]
