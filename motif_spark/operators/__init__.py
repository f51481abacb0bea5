"""Graph construction, counting, mining, the decision process, the network and its training."""
