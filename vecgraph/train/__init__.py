"""Losses, gradients and the joint training loop of the learned quantizer."""
