"""Threat propagation over software supply-chain build histories, and training-data operators."""
