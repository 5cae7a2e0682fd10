"""What the routed method is compared with."""
