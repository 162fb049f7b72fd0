"""Relations over words, graph kernels and the operators built on them."""
