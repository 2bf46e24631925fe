"""Networks, policies, simulator and training."""
