"""The agent, its network, its memories and its training."""
