"""What the full system is compared with: chunk retrieval, latest two-hop context, latest-state pattern queries."""
