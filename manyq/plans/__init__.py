"""How fork batches run: policies, kernels, the buffered engine, and the systems it is compared with."""
