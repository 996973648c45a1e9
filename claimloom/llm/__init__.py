"""Training-data operators; nothing else in claimloom imports this subpackage."""
