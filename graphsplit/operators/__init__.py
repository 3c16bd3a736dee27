"""Steps of the methods: in-task kernels for small graphs, and DataFrame supersteps for large ones."""
