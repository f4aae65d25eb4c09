"""One query for each corpus operator, over the whole of its table."""

from __future__ import annotations

from navspark.llm import decontam, html_layout, line_rules, line_runs, packing_dp, pii, quality_mil, simhash_vp, token_tree, warc
from navspark.llm.common import table


def op1_warc_salvage(spark, sf_dir):
    return warc.op1_result(spark, table(spark, sf_dir, "pages"))


def op2_personal_data(spark, sf_dir):
    return pii.op2_result(table(spark, sf_dir, "documents"))


def op3_quality_mil(spark, sf_dir):
    return quality_mil.op3_result(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_packing_dp(spark, sf_dir):
    return packing_dp.pack(table(spark, sf_dir, "documents"))


def op5_html_layout(spark, sf_dir):
    return html_layout.op5_result(table(spark, sf_dir, "pages"))


def op6_line_rules(spark, sf_dir):
    return line_rules.op6_result(table(spark, sf_dir, "documents"))


def op7_token_tree(spark, sf_dir):
    return token_tree.op7_result(table(spark, sf_dir, "documents"))


def op8_simhash_vp(spark, sf_dir):
    return simhash_vp.op8_result(table(spark, sf_dir, "documents"))


def op9_line_runs(spark, sf_dir):
    return line_runs.op9_result(table(spark, sf_dir, "documents"))


def op10_decontamination(spark, sf_dir):
    return decontam.op10_result(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries():
    return {
        "op1_warc_salvage": op1_warc_salvage,
        "op2_personal_data": op2_personal_data,
        "op3_quality_mil": op3_quality_mil,
        "op4_packing_dp": op4_packing_dp,
        "op5_html_layout": op5_html_layout,
        "op6_line_rules": op6_line_rules,
        "op7_token_tree": op7_token_tree,
        "op8_simhash_vp": op8_simhash_vp,
        "op9_line_runs": op9_line_runs,
        "op10_decontamination": op10_decontamination,
        "pipeline": pipeline,
    }


def oracle_sql():
    return {"op1_warc_salvage": warc.OP1_SQL, "op6_line_rules": line_rules.OP6_SQL, "op9_line_runs": line_runs.OP9_SQL, "op10_decontamination": decontam.OP10_SQL}
