"""Sequential numpy kernels that run inside one segment."""
