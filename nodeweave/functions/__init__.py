"""Local matrix functions: everything here is numpy on small matrices (variables or nodes)."""
