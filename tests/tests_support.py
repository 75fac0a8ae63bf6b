from test_kernels import READS, WANT, reads_frame

__all__ = ["READS", "WANT", "reads_frame"]
