"""Column builders: curve keys, boxes, costs, portable hashes; and their SQL registration."""
