"""Vocabulary of the engine: operation classes, stages, terms, and schemas of its tables."""

from __future__ import annotations

#: Operation classes in the order of their codes.
OPS = ("INT_ALU", "INT_MUL", "INT_DIV", "FP_ALU", "FP_MUL", "FP_DIV", "LOAD", "STORE", "BRANCH", "READ", "MOV", "NULL")
CODE = {name: k for k, name in enumerate(OPS)}
LOAD, STORE, BRANCH = CODE["LOAD"], CODE["STORE"], CODE["BRANCH"]
REGISTERS = 32

#: Stages by order within an instruction.
STAGES = ("F", "D", "E", "M", "EC", "C")
STAGE_ORD = {s: k for k, s in enumerate(STAGES)} | {"BF": 0, "BC": 5, "MS": 3, "MC": 4}

#: Categories of a breakdown.
TERM_OF_OP = {"INT_ALU": "int", "INT_MUL": "int", "INT_DIV": "int", "FP_ALU": "fp", "FP_MUL": "fp", "FP_DIV": "fp", "LOAD": "load", "STORE": "store", "BRANCH": "branch", "READ": "read", "MOV": "mov", "NULL": "null"}

TRACE = (
    "program_id int, seq bigint, pc bigint, op_class string, src1 int, src2 int, dst int, addr bigint, iline bigint, "
    "imem_cycles int, dmem_cycles int, is_branch boolean, mispredicted boolean, wrong_path boolean, block_no bigint, slot int, n_bytes int, predicated boolean"
)
EDGE = "program_id int, src_seq bigint, src_stage string, dst_seq bigint, dst_stage string, kind string, w int"
RUN = "program_id int, lane int, cycles bigint, instrs bigint"
PATH = "program_id int, lane int, hop bigint, src_seq bigint, src_stage string, dst_seq bigint, dst_stage string, kind string, term string, w bigint"
