"""Storage forms, setup measures, building blocks and element-wise operators of sparse matrices."""
