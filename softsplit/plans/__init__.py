"""Plans of the soft splitter: forward pass, cell statistics, assignment, Gram sums, and their Arrow kernels."""
