"""Single-task algorithms for graphs whose size has been checked."""
