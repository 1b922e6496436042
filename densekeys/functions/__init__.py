"""Column functions and array kernels: encoding, linear and mixing hashes, bucket graphs, rank."""
