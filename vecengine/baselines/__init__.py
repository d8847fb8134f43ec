"""What the byte-table quantizer is compared with."""
