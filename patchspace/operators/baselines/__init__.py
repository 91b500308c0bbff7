"""Methods that the index is compared with."""
