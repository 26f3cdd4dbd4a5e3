"""Fine elements: each identifier, weight and offset in as few bits as it needs."""
