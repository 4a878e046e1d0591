"""Outlier scoring for large tables on Spark: exact low-precision operators, automatic batching, fused kernels."""
