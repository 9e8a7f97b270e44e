"""Networks and task sets derived from tables; edge-list readers and writers."""
