"""What the partitioned engine is compared with."""
