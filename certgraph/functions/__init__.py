"""Pure Python and numpy kernels that run inside one task, and their SQL registration."""
